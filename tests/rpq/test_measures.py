"""Measures, logs and counters."""

from rpqspark import queries
from rpqspark.baselines import product
from rpqspark.exec import planner
from rpqspark.exec.options import RpqOptions, RunStats
from rpqspark.graph import sources
from rpqspark.graph.model import Graph
from rpqspark.metrics import bench, check, cost
from rpqspark.workload import log
from rpqspark.workload.table1 import FREQUENCIES


def test_summaries(spark):
    runs = spark.createDataFrame([("q1", "v * c", "core", 1.0), ("q2", "v * c", "core", 3.0), ("q3", "v * v", "core", 90.0), ("q1", "v * c", "other", 0.5), ("q2", "v * c", "other", 2.0), ("q3", "v * v", "other", 99.0)], "query string, pattern string, method string, seconds double")
    total = {r.method: r for r in bench.summarise(runs).filter("ends IS NULL").collect()}
    assert (total["core"].queries, total["core"].median, total["core"].timeouts) == (3, 3.0, 1) and round(total["core"].average, 3) == round(64 / 3, 3)
    best = {r.pattern: (r.method, round(r.share, 3)) for r in bench.winners(runs).collect()}
    assert best == {"v * c": ("other", 0.667), "v * v": ("core", 0.333)}
    wide = {r.measure: r for r in bench.table(runs).collect()}
    assert wide["timeouts"].core == 1.0 and wide["median"].other == 2.0
    a = runs.select("query")
    assert tuple(check.difference(a, a).first()) == (0, 0) and check.difference(a, a.distinct()).first().extra == 3


def test_work_is_counted_once_a_product_node(spark):
    g = sources.metro(spark)
    seen, _, _ = product.reached(g, "l5+/bus")
    row, stats = cost.counters(g, "^bus/l5*/l5", o="Baq")
    assert stats.states_per_visit >= 1 and row.first().answers == 2
    # Backward from one end: every state of a node is entered once, so states equal product nodes.
    size = cost.product_size(g, "^bus/l5*/l5", o="Baq").first()
    assert stats.states <= size.product_nodes + stats.states_per_visit * 4 and seen.count() > 0
    stats = RunStats()
    planner.evaluate(g, "^bus/l5*/l5", o="Baq", options=RpqOptions(executor="frontier"), stats=stats)
    assert stats.rounds <= 5 and stats.frontier_rows <= stats.states


def test_synthetic_log(spark, sf_dir):
    graphs = {n: sources.load(spark, sf_dir, n) for n in ("web", "pulse", "flow", "trade", "chat", "succ")}
    made = log.generate(graphs, 60)
    assert made == log.generate(graphs, 60) and len({m[0].split(".")[0] for m in made}) >= len(FREQUENCIES)
    runs = log.run(spark, graphs, [m for m in made if m[1] == "chat"][:2])
    assert runs.filter("seconds > 0").count() == runs.count() > 0


def test_product_size_from_an_object_counts_every_state(spark):
    """x -> y -> z by one label and plus: backward from z both states of x and y, and the final one of z."""
    g = Graph.of(spark.createDataFrame([("x", "a", "y"), ("y", "a", "z")], "s string, p string, o string"))
    size = cost.product_size(g, "a+", o="z").first()
    assert (size.product_nodes, size.product_edges) == (5, 4)
    assert cost.product_size(g, "a+", s="x").first().product_nodes == 3


def test_the_index_is_searched_beyond_one_shard(spark):
    """A graph over one shard is searched on the index of the path's labels, or in rounds over many shards; the answers are the same."""
    rows = [(f"n{i}", "ab"[i % 3 == 0], f"n{(i * 7 + j) % 40}") for i in range(40) for j in range(2)] + [(f"n{i}", "c", f"m{i}") for i in range(40)]
    g = Graph.of(spark.createDataFrame(rows, "s string, p string, o string")).stored("shards")
    for path, s, o in (("a/b", None, None), ("a*/b", None, "n3"), ("^b/a+", "n3", None), ("(a|b)*", "m1", None), ("a/^a", "n1", "n2"), ("b*", None, None)):
        wanted = planner.evaluate(g, path, s, o)
        wanted = sorted(map(tuple, wanted.collect()))
        for most in (100, 5):
            stats = RunStats()
            got = planner.evaluate(g, path, s, o, RpqOptions(executor="ring", kernel_edges=most, index_only=True), stats=stats)
            assert sorted(map(tuple, got.collect())) == wanted, (path, most)
            assert (stats.rounds > 0) == (most == 5), (path, most)


def test_a_timed_log_has_no_limits(spark, sf_dir, monkeypatch):
    asked = []
    monkeypatch.setattr(log, "_run", lambda g, method, s, path, o, options: asked.append(options) or 1)
    assert queries.timed_log(spark, sf_dir).first().queries == 20
    assert len(asked) == 40 and all(o.limit is None and o.timeout_s is None and o.index_only for o in asked)
