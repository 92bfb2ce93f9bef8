"""Limits, time limits, the log's models, and tables that are dropped."""

import numpy as np
import pyarrow as pa
import pytest

from rpqspark.automaton import bitparallel
from rpqspark.exec import kernel, planner, rare, reach
from rpqspark.exec import store as stores
from rpqspark.exec.options import RpqOptions, RunStats
from rpqspark.graph.model import Graph
from rpqspark.lang import patterns
from rpqspark.lang.parser import parse
from rpqspark.sql import bgp
from rpqspark.workload import log, oracle
from rpqspark.workload.table1 import FREQUENCIES

RING_OF = [(f"n{i}", "a", f"n{(i + 1) % 60}") for i in range(60)]


def test_kernel_gives_up_in_time():
    rows = pa.table({c: pa.array([e[i] for e in RING_OF]) for i, c in enumerate("spo")})
    t = bitparallel.compile(parse("a+"))
    search = kernel.Search(kernel.local(rows, t, True), t.arrays(True), t.chunk_bits, True)
    search.deadline = 0.0
    with pytest.raises(TimeoutError):
        search.run(np.array([0]), np.array([0]), np.array([t.nfa.mask(t.nfa.last)]), t.initial)


def test_limit_on_each_executor(spark):
    g = Graph(spark.createDataFrame(RING_OF, "s string, p string, o string").coalesce(1))
    for executor in ("kernel", "ring"):
        options = RpqOptions(executor=executor, limit=7)
        assert planner.evaluate(g, "a+", options=options).count() == 7
        assert planner.evaluate(g, "a*", s="n3", options=options).count() == 7


def test_models_of_the_log():
    per: dict[str, int] = {}
    for pattern, _, q, n in log.models(200):
        assert patterns.classify(q.s, q.path, q.o) == pattern and n > 0
        per[pattern] = per.get(pattern, 0) + n
        assert oracle.model(q.id, pattern, (q.s or q.o or "").split(":")[0], n)
    share = 200 / sum(FREQUENCIES.values())
    assert per == {p: max(1, round(n * share)) for p, n in FREQUENCIES.items()}


def test_past_tables_are_dropped(spark):
    a, kept = stores.Store(spark, "rpq"), stores.Store(spark, "graph")
    for s in (a, kept):
        s.save(spark.range(3), "t")
    stores.release(spark)
    assert a not in stores.Store.live and kept in stores.Store.live
    assert spark.read.parquet(kept.path("t")).count() == 3
    with pytest.raises(Exception):
        spark.read.parquet(a.path("t")).count()
    kept.drop()


def _knots(spark):
    """Two rings with a way from one to the other, ways in, and ways out."""
    ring = lambda k, n: [(f"{k}{i}", "a", f"{k}{(i + 1) % n}") for i in range(n)]
    rows = [*ring("x", 8), *ring("y", 6), ("x3", "a", "y0"), ("i", "a", "x0"), ("j", "a", "i"), ("j", "a", "k"), ("y2", "a", "z"), ("z", "b", "w"), ("x1", "b", "x5")]
    return Graph.of(spark.createDataFrame(rows, "s string, p string, o string"))


def test_pairs_through_a_large_part_are_one_block(spark, monkeypatch):
    """With both ends open, starts and ends of a strongly connected part are joined, not searched; no pair comes twice."""
    monkeypatch.setattr(kernel, "PART", 3)
    g = _knots(spark)
    tables = bitparallel.compile(parse("a+"))
    found = kernel.both_open(spark, kernel.fetch(g, ["a"], 100), tables, False)
    assert len(found.blocks) >= 2 and found.known() > found.rest.count()
    for path in ("a*", "a+", "a+/b", "a+/b/a*", "(a/^b)*"):
        want = sorted(map(tuple, planner.evaluate(g, path, options=RpqOptions(executor="kernel", visit="dfs")).collect()))
        for order in ("auto", "fixed"):
            out = planner.evaluate(g, path, options=RpqOptions(executor="kernel", direction=order, order="objects"))
            assert sorted(map(tuple, out.collect())) == want, (path, order)
    # The empty paths of a stored graph's nodes are added without a shuffle of the answers.
    plan = planner.evaluate(g.stored("knots"), "a*", options=RpqOptions(executor="kernel"))._jdf.queryExecution().optimizedPlan().toString()
    assert "Aggregate" not in plan


def test_a_wide_level_is_cut(monkeypatch):
    """What a task holds of a level is bounded in steps, whatever the degree of the nodes; the answers are the same."""
    n = 40
    every = pa.table({"s": [f"n{i}" for i in range(n) for _ in range(n)], "p": ["a"] * n * n, "o": [f"n{j}" for _ in range(n) for j in range(n)]})
    t = bitparallel.compile(parse("a+"))
    search = kernel.Search(kernel.local(every, t, False), t.arrays(False), t.chunk_bits, False)
    monkeypatch.setattr(kernel, "STEPS", 4 * n)
    most, repeat = [], np.repeat
    monkeypatch.setattr(np, "repeat", lambda x, k: most.append(int(np.sum(k))) or repeat(x, k))
    at = np.arange(n)
    o, _ = search.run(at, at, np.full(n, t.initial, np.int64), t.nfa.mask(t.nfa.last))
    assert len(o) == n * n and max(most) <= 4 * n


def test_halves_of_a_split_meet_by_start(spark):
    """A start goes on from all rare edges that it reaches together; a half that fits the kernel takes no rounds."""
    rows = [(f"s{i}", "a", "m") for i in range(6)] + [("m", "a", f"x{i}") for i in range(6)] + [(f"x{i}", "r", f"y{j}") for i in range(6) for j in range(6)] + [(f"y{i}", "b", "z") for i in range(6)]
    g = Graph.of(spark.createDataFrame(rows, "s string, p string, o string"))
    seen = RunStats()
    got = sorted(map(tuple, rare.split_evaluate(g, "a+/r/b+", "r", RpqOptions(executor="frontier"), seen).collect()))
    assert got == sorted([("m", "z"), *[(f"s{i}", "z") for i in range(6)]])
    assert seen.rounds == 0
    assert sorted(map(tuple, rare.split_evaluate(g, "a+/r/b+", "r", RpqOptions(kernel_edges=3), seen).collect())) == got and seen.rounds


def test_starts_are_answered_by_sets_of_ends(spark, monkeypatch):
    """A split is searched once for all starts, also where its label is not rarer than the ends; the pairs are those of a search."""
    rng = np.random.default_rng(3)
    rows = {(f"n{i}", "abr"[k], f"n{j}") for i, j, k in zip(*rng.integers(0, [[60], [60], [3]], (3, 170)))} | {(f"n{i}", "r", f"n{i + 1}") for i in range(60)}
    g = Graph.of(spark.createDataFrame(sorted(rows), "s string, p string, o string")).stored("sets")
    wanted = {x: sorted(map(tuple, planner.evaluate(g, x, options=RpqOptions(visit="dfs", fast_paths=False)).collect())) for x in ("a+/r/b+", "a*/r/b*", "(a|^b)+/r/a?")}
    seen = RunStats()
    monkeypatch.setattr(kernel, "evaluate_local", None)
    for path, pairs in wanted.items():
        got = planner.evaluate(g, path, options=RpqOptions(executor="frontier", rare_times=1), stats=seen)
        assert sorted(map(tuple, got.collect())) == pairs and len(pairs) > 100, path
    assert seen.rounds == 0 and seen.extra["split at"] == "r" and planner.rare_label(parse("a+/r/b+"), g.counts(), 1) is None


def test_sets_of_ends_in_small_ranges(monkeypatch):
    """Ranges, runs of starts and ends, and batches may end anywhere; no pair comes twice."""
    monkeypatch.setattr(reach, "TILE", 3)
    monkeypatch.setattr(reach, "ROWS", 2)
    rng = np.random.default_rng(5)
    for n in (0, 1, 2, 300):
        s, o, k = rng.integers(0, 150, (3, n))
        rows = pa.table({"s": pa.array([f"n{x}" for x in s], pa.string()), "p": pa.array(["ab"[x % 2] for x in k], pa.string()), "o": pa.array([f"n{x}" for x in o], pa.string())})
        t = bitparallel.compile(parse("a*/b/a+"))
        ahead, behind = (kernel.local(rows, t, back) for back in (False, True))
        found = reach.levels(ahead, behind, t, t.label("b"))
        got = [(x, y) for lo in range(0, len(found.ends), 64) for b in reach.tiles(found, pa.array(ahead.names, pa.string()), lo, 1) for xs, ys in zip(*(c.to_pylist() for c in b.columns)) for x in xs for y in ys]
        search, at = kernel.Search(ahead, t.arrays(False), t.chunk_bits, False), np.arange(len(ahead.names))
        a, b = search.run(at, at, np.full(len(at), t.initial, np.int64), t.nfa.mask(t.nfa.last)) if len(at) else (at, at)
        assert sorted(got) == sorted(zip(ahead.names[a], ahead.names[b]))


def test_pairs_are_counted_by_blocks(spark, monkeypatch):
    monkeypatch.setattr(kernel, "PART", 3)
    g = _knots(spark)
    for path in ("a*", "a+", "a+/b", "a/b", "a/^b", "b|a"):
        assert planner.counted(g, path).first().answers == planner.evaluate(g, path, options=RpqOptions(visit="dfs")).count(), path


def test_join_only_paths_are_cut_to_bindings(spark):
    """Beyond the kernel's bound a join-only path is joined for the bindings of its ends; joined sets are not made distinct again."""
    rows = [("x", "a", "y"), *[(f"y{i}" if i else "y", "b", f"m{i}") for i in range(9)], *[(f"m{i}", "c", f"z{j}") for i in range(9) for j in range(2)]]
    g = Graph.of(spark.createDataFrame(rows, "s string, p string, o string")).stored("cut")
    out = bgp.evaluate(g, [("?x", "a", "?y"), ("?y", "b/c", "?z")], RpqOptions(kernel_edges=5))
    assert sorted(map(tuple, out.select("x", "y", "z").collect())) == [("x", "y", "z0"), ("x", "y", "z1")]
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    assert "LeftSemi" in plan and not plan.startswith("Aggregate")
