"""Worked example, parser, automata, and all executors against brute force."""

import random

import pytest

from rpqspark.automaton import bitparallel, epsilon, position, subset
from rpqspark.exec import kernel, planner
from rpqspark.exec.options import RpqOptions, RunStats
from rpqspark.graph import sources
from rpqspark.graph.model import Graph
from rpqspark.lang import patterns, rewrite
from rpqspark.lang.ast import text
from rpqspark.lang.parser import PathError, parse

NODES = ["SA", "UCh", "LH", "BA", "Baq"]


def test_parser_and_rewrites():
    for t in ["a/b*", "(a|^b)+/c?", "^(a/b)", "!(a|^b)", "[a|b]", "()", "a/@n/b", "(a/b)*", "'x y'/<http://z>"]:
        e = parse(t)
        assert parse(text(e)) == e
    assert text(rewrite.push_inverse(parse("^(a/^b*)"))) == "b*/^a"
    assert rewrite.push_inverse(parse("^(^(a/b|c))")) == parse("a/b|c")
    assert text(rewrite.reverse(parse("a/b*|^c"))) == "^b*/^a|c"
    assert text(rewrite.simplify(parse("((a*)*)?/()/b|b"))) == "a*/b|b"
    for bad in ["", "a/", "(a", "a)", "*", "a||b"]:
        with pytest.raises(PathError):
            parse(bad)
    got = [patterns.classify(*q) for q in [(None, "a/b*", "c"), ("c", "a*", None), (None, "(a|b)*", "c"), (None, "^a", None), (None, "a/^b", None), (None, "a|b|c", None), (None, "a*/b*/c*", "x")]]
    assert got == ["v /* c", "c * v", "v |* c", "v ^ v", "v /^ v", "v || v", "v */*/* c"]
    e = rewrite.expand_labels(parse("a/b"), {"a": {"a1", "a2"}, "a1": {"a3"}})
    assert {n for n, _ in rewrite.symbols(e)[0].labels} == {"a", "a1", "a2", "a3"}


def test_position_automaton_of_the_example():
    t = bitparallel.compile(parse("^bus/l5*/l5"))
    assert (t.label("bus", True), t.label("l5"), t.nfa.mask(t.nfa.last)) == (0b0100, 0b0011, 0b0001)
    back = lambda d: t._look(t.R, d)
    assert [back(x) for x in (1, 2, 3)] == [0b0110] * 3
    assert (back(0b0100), back(0b1100), back(0b1000)) == (0b1000, 0b1000, 0)
    assert [back(x) for x in (5, 6, 7)] == [0b1110] * 3


def test_word_example():
    t = bitparallel.compile(parse("a/b*/b"))
    d, seen = t.initial, []
    for c in "abba":
        d = t.forward(d, c)
        seen.append(d)
    assert seen == [0b0100, 0b0011, 0b0011, 0] and [i + 1 for i, x in enumerate(seen) if x & t.final] == [2, 3]


def random_expr(rnd, depth=3, labels="abc"):
    if depth == 0 or rnd.random() < 0.25:
        return rnd.choice(["", "^"]) + rnd.choice(labels) if rnd.random() < 0.85 else rnd.choice(["!(a|b)", "[a|^b]", "!(^c)"])
    k = rnd.randrange(6)
    x = random_expr(rnd, depth - 1)
    if k < 2:
        return f"({x})/({random_expr(rnd, depth - 1)})"
    if k == 2:
        return f"({x})|({random_expr(rnd, depth - 1)})"
    return f"({x})" + "*+?"[k - 3]


def test_automata_agree():
    rnd = random.Random(0)
    for _ in range(150):
        e = parse(random_expr(rnd))
        p, n = position.build(e), epsilon.build(e)
        d = subset.build(n, "abc")
        tables = [bitparallel.compile(e, chunk_bits=b) for b in (1, 2, 3, 8)]
        assert p.m == len(rewrite.symbols(e)) and epsilon.build(rewrite.desugar(e)) is not None
        for _ in range(20):
            w = [(rnd.choice("abc"), rnd.random() < 0.3) for _ in range(rnd.randrange(6))]
            want = n.accepts(w)
            assert p.accepts(w) == want == n.without_empty().accepts(w) == d.accepts(w)
            for t in tables:
                f, b = t.initial, t.final
                for c in w:
                    f = t.forward(f, *c)
                for c in reversed(w):
                    b = t.backward(b, *c)
                assert bool(f & t.final) == want == bool(b & t.initial)
        for states in [{0}, set(range(p.m + 1))]:
            for c in "abc":
                assert p.step(states, c) == set().union(*(p.after(q) for q in states)) & p.targets(c, False)


def test_metro_answers(spark):
    g = sources.metro(spark)
    for ex in ("kernel", "frontier"):
        o = RpqOptions(executor=ex, fast_paths=False)
        assert {r.o for r in planner.evaluate(g, "l5+/bus", s="Baq", options=o).collect()} == {"SA", "UCh"}
        assert {r.s for r in planner.evaluate(g, "^bus/l5*/l5", o="Baq", options=o).collect()} == {"SA", "UCh"}
        assert planner.evaluate(g, "l1|l2|l5", options=o).count() == 10
        assert {(r.s, r.o) for r in planner.evaluate(g, "(l1|l2|l5)+", options=o).collect()} == {(a, b) for a in NODES for b in NODES}
        assert planner.evaluate(g, "(l1|l2|l5)+", s="Baq", o="SA", options=o).first().found is True
    stats = RunStats()
    planner.evaluate(g, "^bus/l5*/l5", o="Baq", options=RpqOptions(executor="frontier"), stats=stats)
    assert stats.states == 3 + 2 + 3 + 1 and stats.rounds == 4


def test_visit_sequence_of_the_kernel(spark):
    t = bitparallel.compile(parse("^bus/l5*/l5"))
    rows = kernel.fetch(sources.metro(spark), ["bus", "l5"], 100)
    search = kernel.Search(kernel.local(rows, t, True), t.arrays(True), t.chunk_bits, True)
    ids = {n: i for i, n in enumerate(search.g.names)}
    import numpy as np

    for order in ("bfs", "dfs"):
        _, found = search.run(np.array([0]), np.array([ids["Baq"]]), np.array([1]), t.initial, order=order)
        assert {search.g.names[i] for i in found} == {"SA", "UCh"} and not search.visited.any()


def brute(edges, path, names):
    """All answers by a search over (node, state) with the empty-transition automaton."""
    n = epsilon.build(parse(path)).without_empty()
    nodes = {x for s, _, o in edges for x in (s, o)}
    out = set()
    for x in nodes:
        seen, todo = {(x, n.start)}, [(x, n.start)]
        while todo:
            v, q = todo.pop()
            if q in n.finals:
                out.add((x, v))
            for a, c, b in n.moves:
                if a == q:
                    for s, p, o in edges:
                        for inverse, i, j in ((False, s, o), (True, o, s)):
                            if i == v and c.holds(p, inverse) and (j, b) not in seen:
                                seen.add((j, b))
                                todo.append((j, b))
    return out


def test_kernel_and_joins_equal_brute_force(spark):
    rnd = random.Random(7)
    for _ in range(5):
        edges = {(f"n{rnd.randrange(5)}", rnd.choice("abc"), f"n{rnd.randrange(5)}") for _ in range(rnd.randrange(1, 12))}
        g = Graph(spark.createDataFrame(sorted(edges), "s string, p string, o string").coalesce(1))
        path = random_expr(rnd, 2)
        want = brute(edges, path, "abc")
        assert {tuple(r) for r in planner.evaluate(g, path).select("s", "o").collect()} == want, path
        assert {r.s for r in planner.evaluate(g, path, o="n1").collect()} == {a for a, b in want if b == "n1"}, path
        assert {r.o for r in planner.evaluate(g, path, s="n1", options=RpqOptions(fast_paths=False)).collect()} == {b for a, b in want if a == "n1"}, path
        assert {r.s for r in planner.evaluate(g, path, s="?x", o="?x").collect()} == {a for a, b in want if a == b}, path
        assert planner.evaluate(g, path, s="n0", o="n2").first().found == (("n0", "n2") in want), path


@pytest.mark.parametrize("options", [
    RpqOptions(executor="frontier", fast_paths=False),
    RpqOptions(executor="frontier", fast_paths=False, order="objects", direction="fixed", prune=False),
    RpqOptions(executor="frontier", fast_paths=False, mask_bits=2, chunk_bits=1, origin_chunks=2),
    RpqOptions(executor="frontier", fast_paths=False, range_start=False, label_pruning=False, merge_states=False),
])
def test_frontier_equals_brute_force(spark, options):
    edges = {("n0", "a", "n1"), ("n1", "b", "n2"), ("n2", "a", "n0"), ("n2", "b", "n2"), ("n3", "a", "n1"), ("n1", "c", "n3"), ("n4", "c", "n4")}
    g = Graph(spark.createDataFrame(sorted(edges), "s string, p string, o string").coalesce(1))
    for path in ["(a/b*)+"]:
        want = brute(edges, path, "abc")
        assert {tuple(r) for r in planner.evaluate(g, path, options=options).select("s", "o").collect()} == want, path
        assert {r.s for r in planner.evaluate(g, path, o="n1", options=options).collect()} == {a for a, b in want if b == "n1"}
        assert {r.o for r in planner.evaluate(g, path, s="n1", options=options).collect()} == {b for a, b in want if a == "n1"}
    for both in (False, True):
        import dataclasses

        o = dataclasses.replace(options, bidirectional=both)
        assert planner.evaluate(g, "(a/b*)+", s="n0", o="n2", options=o).first().found == (("n0", "n2") in brute(edges, "(a/b*)+", "abc"))
