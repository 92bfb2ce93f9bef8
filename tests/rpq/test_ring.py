"""The index executor: the order of visits of the worked example, and all answers against brute force."""

import random

import pyarrow as pa
import pytest
from test_conditions import brute
from test_core import random_expr

from rpqspark.automaton import bitparallel
from rpqspark.exec import planner, ring, seek
from rpqspark.exec.options import RpqOptions
from rpqspark.graph import sources
from rpqspark.graph.model import Graph
from rpqspark.lang import rewrite
from rpqspark.lang.parser import parse
from rpqspark.workload.table1 import QUERIES

RING = RpqOptions(executor="ring", fast_paths=False)


#: Lines run both ways.
METRO = sorted({e for s, p, o in sources.METRO for e in ((s, p, o), *([(o, p, s)] if p != "bus" else []))})


def shard(edges):
    return ring.Shard.of(pa.table({c: pa.array([e[i] for e in edges], pa.string()) for i, c in enumerate("spo")}))


def test_visits_of_the_worked_example():
    t = bitparallel.compile(parse("^bus/l5*/l5"))
    s = shard(METRO)
    at = {n: i for i, n in enumerate(s.names)}
    got = [(s.names[v], d) for v, d in ring.visits(s, t, at["Baq"])]
    assert got[0] == ("BA", 0b0110) and sorted(got[1:4]) == [("Baq", 0b0110), ("SA", 0b0110), ("SA", 0b1000)] and got[4:] == [("UCh", 0b1000)]
    # The label l5 comes before the inverse bus, so SA gets the closure's states before the initial one.
    assert got.index(("SA", 0b0110)) < got.index(("SA", 0b1000))
    deep = [(s.names[v], d) for v, d in ring.visits(s, t, at["Baq"], "dfs")]
    assert {v for v, d in deep if d & t.initial} == {"SA", "UCh"}
    search = ring.Search(s, t)
    assert [s.names[i] for i in search.run(at["Baq"], at["Baq"] + 1)] == ["SA", "UCh"]
    assert search.counts["steps"] == 4 and search.counts["pruned"] > 0
    assert all((a == b).all() for a, b in zip(search.seen, search.fresh))


def test_searches_equal_brute_force():
    rnd = random.Random(0)
    for _ in range(80):
        n = rnd.randrange(1, 9)
        edges = sorted({(f"n{rnd.randrange(n)}", rnd.choice("abc"), f"n{rnd.randrange(n)}") for _ in range(rnd.randrange(1, 14))})
        s, path = shard(edges), random_expr(rnd, 2)
        t, m = bitparallel.compile(parse(path)), bitparallel.compile(rewrite.reverse(parse(path)))
        want, v = brute(edges, path), len(s.names)
        ahead, behind = ring.Search(s, t), ring.Search(s, m)
        same = {(x, x) for x in s.names} if t.nfa.nullable else set()
        assert {(s.names[a], s.names[o]) for o in range(v) for a in ahead.run(o, o + 1)} | same == want, (edges, path)
        assert {(s.names[a], s.names[o]) for a in range(v) for o in behind.run(a, a + 1)} | same == want
        assert {s.names[a] for a in ahead.run(0, v)} | {a for a, _ in same} == {a for a, _ in want}
        for o in range(v):
            for lo in range(v):
                least = min([i for i, x in enumerate(s.names) if i >= lo and (x, s.names[o]) in want], default=None)
                assert ring.next_subject(s, t, m, lo, o) == least


def test_must_pass_on_the_index():
    edges = [("n0", "a", "n1"), ("n1", "a", "n2"), ("n0", "a", "n3"), ("n3", "a", "n2"), ("n4", "a", "n1")]
    s, t = shard(edges), bitparallel.compile(parse("a/@n1/a"))
    search = ring.Search(s, t)
    assert {(s.names[a], s.names[o]) for o in range(5) for a in search.run(o, o + 1)} == brute(edges, "a/@n1/a")


def test_executor(spark):
    g = Graph(spark.createDataFrame(METRO, "s string, p string, o string").coalesce(1))
    want = brute(METRO, "l5+/bus")
    ask = lambda **k: {tuple(r) for r in planner.evaluate(g, "l5+/bus", options=RING, **k).collect()}
    assert ask() == want and ask(s="Baq") == {("SA",), ("UCh",)} and ask(o="SA") == {(a,) for a, b in want if b == "SA"}
    assert ask(s="Baq", o="SA") == {(True,)} and ask(s="LH", o="LH") == {(("LH", "LH") in want,)} and ask(s="x", o="SA") == {(False,)}
    assert planner.evaluate(g, "(l1|l2|l5)*", options=RING).count() == 25
    assert seek.next_solution(g, "l5+/bus", "o", "T", s="Baq", options=RING).first().value == "UCh"


@pytest.mark.parametrize("query_id", ["w02b", "w12", "w21", "w22"])
def test_graphs_over_one_shard_are_answered_all_the_same(spark, sf_dir, query_id):
    q = QUERIES[query_id]
    g = Graph.of(sources.load(spark, sf_dir, q.graph).edges)
    over = RpqOptions(executor="ring", fast_paths=False, kernel_edges=20)
    got = planner.evaluate(g, q.path, q.s, q.o, over)
    want = planner.evaluate(sources.load(spark, sf_dir, q.graph), q.path, q.s, q.o)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_next_binding_over_one_shard(spark, sf_dir):
    from rpqspark.exec import seek

    g = Graph.of(sources.load(spark, sf_dir, "web").edges)
    got = [seek.next_solution(g, "on_host/parent*", "s", "page:5", o="host:com", options=RpqOptions(executor="ring", kernel_edges=n)).first().value for n in (20, 2_000_000)]
    assert got[0] == got[1] is not None


def test_closure_of_a_step_through_a_large_part(spark, monkeypatch):
    """With both ends open the pairs through a strongly connected part are not searched one by one; a limit ends what gives enough."""
    from rpqspark.exec import kernel

    monkeypatch.setattr(kernel, "PART", 3)
    rows = [(f"x{i}", "a", f"x{(i + 1) % 6}") for i in range(6)] + [("i", "a", "x0"), ("j", "a", "i"), ("j", "a", "k"), ("x2", "a", "z"), ("z", "a", "w"), ("x1", "b", "j")]
    g = Graph.of(spark.createDataFrame(rows, "s string, p string, o string"))
    searched, answers = [], ring.answers
    monkeypatch.setattr(ring, "answers", lambda g, t, ends, *a, **k: searched.append(len(ends)) or answers(g, t, ends, *a, **k))
    for path in ("a+", "a*", "(a|b)+"):
        got = sorted(map(tuple, planner.evaluate(g, path, options=RpqOptions(executor="ring", fast_paths=False)).collect()))
        assert got == sorted(map(tuple, planner.evaluate(g, path, options=RpqOptions(executor="kernel", visit="dfs")).collect())), path
    assert max(searched[:2]) <= 3
    assert planner.evaluate(g, "a+", options=RpqOptions(executor="ring", limit=9)).count() == 9
