"""Ends, sets, node conditions and unknown constants on every executor, against a search over (node, position)."""

import random

import pytest

from rpqspark.automaton import position
from rpqspark.exec import planner
from rpqspark.exec.options import RpqOptions, RunStats
from rpqspark.graph.model import Graph
from rpqspark.lang.parser import parse
from rpqspark.sql import bgp, surface


def brute(edges, path, allowed=None):
    """All (s, o) by single steps over (node, position); positions are entered where they may be."""
    n, nodes = position.build(parse(path)), {x for s, _, o in edges for x in (s, o)}
    may = lambda v, q: (not allowed or q not in allowed or v in allowed[q]) and n.arrive.get(q, v) == v
    out = {(x, x) for x in nodes} if n.nullable else set()
    for x in nodes:
        seen, todo = {(x, 0)}, [(x, 0)]
        while todo:
            v, q = todo.pop()
            for s, p, o in edges:
                for inverse, a, b in ((False, s, o), (True, o, s)):
                    for t in n.after(q) & n.targets(p, inverse) if a == v else ():
                        if may(b, t) and (b, t) not in seen:
                            seen.add((b, t))
                            todo.append((b, t))
        out |= {(x, v) for v, q in seen if q in n.last}
    return out


EXECUTORS = {
    "kernel": RpqOptions(fast_paths=False),
    "frontier": RpqOptions(executor="frontier", fast_paths=False),
    "shuffled": RpqOptions(executor="frontier", fast_paths=False, broadcast_rows=0, order="objects", origin_chunks=2),
    "bidirectional": RpqOptions(executor="frontier", fast_paths=False, bidirectional=True),
}
ROWS = [("n0", "a", "n1"), ("n1", "a", "n2"), ("n0", "a", "n3"), ("n3", "a", "n2"), ("n2", "b", "n0"), ("n2", "b", "n4"), ("n4", "c", "n1"), ("n4", "a", "n4")]
CASES = [("a/a", None), ("a/a", {1: {"n3"}}), ("(a|b)+/c?", {1: {"n1", "n2"}, 2: {"n4"}}), ("a/@n3/a", None), ("a*/b", {1: {"n3", "n2"}}), ("^a/b*", {2: set()})]


@pytest.fixture(scope="module")
def small(spark):
    return Graph(spark.createDataFrame(ROWS, "s string, p string, o string").coalesce(1))


def named(spark, nodes):
    return spark.createDataFrame([(n,) for n in sorted(nodes)], "node string").coalesce(1)


@pytest.mark.parametrize("name, case", [("kernel", 0), ("kernel", 3), ("frontier", 1), ("frontier", 2), ("frontier", 3), ("shuffled", 4), ("bidirectional", 1), ("bidirectional", 3), ("bidirectional", 4)])
def test_ends_and_conditions(spark, small, name, case):
    path, allowed = CASES[case]
    want, options = brute(ROWS, path, allowed), EXECUTORS[name]
    ok = {q: named(spark, v) for q, v in allowed.items()} if allowed else None
    ask = lambda **k: {tuple(r) for r in planner.evaluate(small, path, options=options, node_filter=ok, **k).collect()}
    for s, o in (("n0", "n2"), ("n2", "n2")):
        assert ask(s=s, o=o) == {((s, o) in want,)}
    if name == "bidirectional":
        return
    assert ask() == want
    assert ask(o="n2") == {(a,) for a, b in want if b == "n2"}
    assert ask(s="n0") == {(b,) for a, b in want if a == "n0"}
    if case == 2:
        some = {"n0", "n2"}
        assert ask(s="?x", o="?x") == {(a,) for a, b in want if a == b}
        assert ask(o_set=named(spark, some)) == {(a,) for a, b in want if b in some}
        assert ask(s_set=named(spark, some)) == {(b,) for a, b in want if a in some}
        assert ask(s_set=named(spark, some), o="n4") == {(b,) for a, b in want if a in some and b == "n4"}
        assert ask(o_set=named(spark, some), s="n1") == {(a,) for a, b in want if b in some and a == "n1"}
        assert ask(s_set=named(spark, {"n0", "n4"}), o_set=named(spark, some)) == {(a,) for a, b in want if b in some and a in ("n0", "n4")}


@pytest.mark.parametrize("options", [RpqOptions(zero_length_unknown="self"), RpqOptions(zero_length_unknown="self", fast_paths=False), RpqOptions(zero_length_unknown="self", executor="frontier", fast_paths=False)])
def test_unknown_constants(spark, small, options):
    ask = lambda path, **k: {tuple(r) for r in planner.evaluate(small, path, options=options, **k).collect()}
    for path in ("a*",):
        assert ask(path, s="z") == {("z",)} == ask(path, o="z")
        assert ask(path, s="z", o="z") == {(True,)} and ask(path, s="z", o="n0") == {(False,)}
        assert ("n0",) in ask(path, s="n0") and ("z",) not in ask(path, s="n0")
    assert ask("a+", s="z") == set() and ask("a+", s="z", o="z") == {(False,)}
    assert ask("a*", s_set=named(spark, {"z", "n4"})) == {("z",), ("n4",)}


def test_limit_ends_the_rounds_early(spark):
    chain = Graph(spark.createDataFrame([(f"n{i:03}", "a", f"n{i + 1:03}") for i in range(40)], "s string, p string, o string").coalesce(1))
    for side in ({"o": "n040"}, {"s": "n000"}):
        stats = RunStats()
        got = planner.evaluate(chain, "a+", options=RpqOptions(executor="frontier", limit=5), stats=stats, **side)
        assert got.count() == 5 and stats.rounds <= 7
    stats = RunStats()
    assert planner.evaluate(chain, "a+", o="n040", options=RpqOptions(executor="frontier"), stats=stats).count() == 40 and stats.rounds == 41


def test_small_frontiers_leave_the_edges_in_place(spark, small):
    from rpqspark.automaton import bitparallel
    from rpqspark.automaton.bitparallel import Masks
    from rpqspark.exec import backward, state
    from pyspark.sql import functions as F

    t = bitparallel.compile(parse("a/b*"))
    front = backward.seeds_of(small, Masks(t), named(spark, {"n0"}), t.nfa.mask(t.nfa.last))
    plan = state.step(F.broadcast(front), backward.steps(small, Masks(t), True, RpqOptions()), Masks(t), [], True)._jdf.queryExecution().executedPlan().toString()
    # Nothing is exchanged by the end that the join is on.
    assert "BroadcastHashJoin" in plan and "hashpartitioning(at" not in plan


def test_random_graphs(spark):
    rnd = random.Random(11)
    for _ in range(2):
        edges = sorted({(f"n{rnd.randrange(5)}", rnd.choice("ab"), f"n{rnd.randrange(5)}") for _ in range(10)})
        g = Graph(spark.createDataFrame(edges, "s string, p string, o string").coalesce(1))
        path = rnd.choice(["(a|b)+", "a*/b", "a/^b*", "(a/b)*"])
        allowed = {rnd.choice([1, 2]): {f"n{i}" for i in range(5) if rnd.random() < 0.6}}
        want = brute(edges, path, allowed)
        ok = {q: named(spark, v) for q, v in allowed.items()}
        for options in (EXECUTORS["frontier"], EXECUTORS["bidirectional"]):
            assert planner.evaluate(g, path, "n0", "n2", options, node_filter=ok).first().found == (("n0", "n2") in want), (edges, path, allowed)
        assert {tuple(r) for r in planner.evaluate(g, path, options=EXECUTORS["frontier"], node_filter=ok).collect()} == want, (edges, path, allowed)


def test_patterns_with_one_variable_at_both_ends(spark, small):
    rows = lambda df: {tuple(r) for r in df.collect()}
    assert rows(bgp.evaluate(small, [("?x", "a/a/b", "?x")])) == {("n0",)}
    assert rows(bgp.evaluate(small, [("?x", "(a|b)+", "?x")])) == {(a,) for a, b in brute(ROWS, "(a|b)+") if a == b}
    got = bgp.evaluate(small, [("?x", "a", "?y"), ("?x", "(a|b)+", "?x")])
    assert rows(got.select("x", "y")) == {(s, o) for s, p, o in ROWS if p == "a" and (s, s) in brute(ROWS, "(a|b)+")}


def test_sql_takes_only_what_its_own_query_demands(spark, small):
    small.edges.createOrReplaceTempView("cond_graph")
    spark.createDataFrame([("c", "n2"), ("d", "n4")], "s string, k string").createOrReplaceTempView("cond_z")
    all_of = brute(ROWS, "a/b")
    ask = lambda text: {tuple(r) for r in surface.sql(spark, text).collect()}
    call = "rpq(graph => 'cond_graph', path => 'a/b')"
    assert ask(f"SELECT t.s, t.o FROM {call} t JOIN (SELECT k FROM cond_z WHERE s = 'd') q ON t.o = q.k") == {x for x in all_of if x[1] == "n4"}
    assert ask(f"SELECT t.s FROM {call} t JOIN cond_z ON t.o = cond_z.k WHERE cond_z.s = 'd'") == {(a,) for a, b in all_of if b == "n4"}
    assert ask(f"SELECT t.o FROM {call} t WHERE t.s = 'n1'") == {(b,) for a, b in all_of if a == "n1"}
    assert ask(f"SELECT o FROM {call} WHERE s = 'n1' AND o = 'n4'") == {("n4",)}
    assert ask(f"SELECT k FROM cond_z WHERE s = 'd' AND EXISTS (SELECT 1 FROM {call} t WHERE t.o = cond_z.k)") == {("n4",)}
    assert ask(f"SELECT t.s FROM {call} t WHERE t.s = 'n1' OR t.s = 'n3'") == {(a,) for a, b in all_of if a in ("n1", "n3")}
    plan = surface.sql(spark, f"SELECT t.o FROM {call} t WHERE t.s = 'n1'")
    assert "s" not in plan.columns


def test_recursion_grows_until_nothing_is_new(spark):
    from rpqspark.baselines import rcte

    chain = Graph(spark.createDataFrame([(f"n{i}", "a", f"n{i + 1}") for i in range(10)], "s string, p string, o string").coalesce(1))
    assert rcte.evaluate(chain, "a+", "n0").count() == 10
    with pytest.raises(ValueError):
        rcte.evaluate(chain, "a+", "n0", max_depth=6)


def test_rare_labels():
    counts = {"a": 100, "b": 90, "r": 5, "q": 4}
    pick = lambda path, times=4: planner.rare_label(parse(path), counts, times)
    assert pick("a+/r/b+") == "r" and pick("a+/r/q/b+") == "q"
    assert pick("a+/r/r/b+") is None and pick("a+/^r/b+") is None and pick("r/b+") is None
    assert pick("a+/r/b+", 40) is None and pick("(a/r)+") is None


def test_open_ends_through_a_node(spark):
    """Beyond the kernel's bound too, a node that every path passes is searched from both of its sides."""
    rng = random.Random(12)
    edges = sorted({(f"n{rng.randrange(9)}", rng.choice("abc"), f"n{rng.randrange(9)}") for _ in range(40)})
    g = Graph.of(spark.createDataFrame(edges, "s string, p string, o string"))
    seen = RunStats()
    for path in ("a/@n3/b", "(a|b)+/@n3/c", "a/^b/@n3/c+/@n4/a", "a/@n3/b*"):
        got = sorted(map(tuple, planner.evaluate(g, path, options=RpqOptions(kernel_edges=3), stats=seen).collect()))
        assert got == sorted(map(tuple, planner.evaluate(g, path, options=RpqOptions(executor="kernel")).collect())), path
        if path == "a/@n3/b":
            assert seen.rounds == 0  # no round of the frontier


def test_pairs_of_one_middle_node_are_not_made_distinct(spark):
    """A step with one object a subject: pairs come from a join alone; else they are made distinct."""
    edges = [("a", "p", "m"), ("b", "p", "m"), ("c", "p", "n"), ("x", "q", "m"), ("y", "q", "m"), ("x", "q", "n"), ("z", "r", "m"), ("z", "r", "n")]
    g = Graph.of(spark.createDataFrame(edges, "s string, p string, o string"))
    once = planner.evaluate(g, "p/^q")
    assert sorted(map(tuple, once.collect())) == [("a", "x"), ("a", "y"), ("b", "x"), ("b", "y"), ("c", "x")]
    twice = planner.evaluate(g, "r/^q")
    assert [x._jdf.queryExecution().optimizedPlan().toString().startswith("Aggregate") for x in (once, twice)] == [False, True]
    assert sorted(map(tuple, twice.collect())) == [("z", "x"), ("z", "y")]
