"""Baselines, sources and sinks, SQL, and streams on small inputs."""

import pytest

from rpqspark import queries
from rpqspark.baselines import alp, closure, joins, pernode, product, rcte
from rpqspark.exec import planner
from rpqspark.exec.options import RpqOptions
from rpqspark.graph import datasource, io, sources
from rpqspark.graph.model import Graph
from rpqspark.sql import surface
from rpqspark.workload.table1 import QUERIES

EDGES = [("n0", "a", "n1"), ("n1", "b", "n2"), ("n2", "a", "n0"), ("n3", "a", "n1"), ("n1", "c", "n3")]


@pytest.fixture(scope="module")
def tiny(spark):
    return Graph(spark.createDataFrame(EDGES, "s string, p string, o string").coalesce(1))


def rows(df):
    return {tuple(r) for r in df.collect()}


def test_baselines_agree(spark, tiny):
    for path in ("a/(b|c)+",):
        want = rows(planner.evaluate(tiny, path))
        for a in ("position", "epsilon", "subset"):
            assert rows(product.evaluate(tiny, path, automaton=a)) == want
        assert rows(alp.evaluate(tiny, path)) == rows(pernode.evaluate(tiny, path)) == want
        assert rows(rcte.evaluate(tiny, path, "n0", 6)) == {(o,) for s, o in want if s == "n0"}
    rel = tiny.edges.select("s", "o")
    assert rows(closure.semi_naive(rel)) == rows(closure.squaring(rel)) == rows(planner.evaluate(tiny, "(a|b|c)+"))
    assert joins.evaluate(tiny, "a/b").count() == 2


def test_files_and_datasource(spark, tiny, tmp_path):
    want = set(EDGES)
    for f in ("parquet", "orc", "json", "csv"):
        io.write_result(tiny.edges, str(tmp_path / f), f)
        assert rows(io.read_triples(spark, str(tmp_path / f), f).edges) == want
    (tmp_path / "x.nt").write_text('<n0> <a> <n1> .\n<n1> <says> "hi \\" there"@en .\nbroken\n')
    assert rows(io.read_nt(spark, str(tmp_path / "x.nt")).edges) == {("n0", "a", "n1"), ("n1", "says", 'hi \\" there')}
    io.write_clustered(tiny, str(tmp_path / "c"), hot_labels=1)
    assert rows(io.read_clustered(spark, str(tmp_path / "c")).edges) == want
    assert rows(io.read_clustered(spark, str(tmp_path / "c"), ["a"]).edges) == {e for e in want if e[1] == "a"}
    (tmp_path / "t.tsv").write_text("".join("\t".join(e) + "\n" for e in EDGES))
    datasource.register(spark)
    got = spark.read.format("triples").option("path", str(tmp_path / "t.tsv")).load()
    assert rows(got.filter("p = 'a'")) == {e for e in want if e[1] == "a"}


def test_sql_and_fluent(spark, tiny):
    io.register_graph(tiny, "tiny")
    got = surface.sql(spark, "SELECT t.o FROM rpq(graph => 'tiny', path => 'a/b') t WHERE t.s = 'n3'")
    assert rows(got) == {("n2",)}
    assert rows(tiny.path("(a/b)+").from_("n0").run()) == {("n2",)}
    assert "joins" in tiny.path("a/b").explain() and "kernel" not in tiny.path("a/b").explain()
    with pytest.raises(ValueError):
        surface.sql(spark, "SELECT * FROM rpq(graph => 'tiny')")


def test_edge_cases(spark, tiny):
    ask = lambda path, **k: rows(planner.evaluate(tiny, path, **k))
    assert ask("zz+", o="n1") == set() == ask("a*", o="nowhere") and ask("zz*", o="n1") == {("n1",)}
    assert len(ask("()")) == 4 and ask("a*", s="n9", o="n9") == {(False,)}
    assert planner.evaluate(tiny, "(a|b|c)+", options=RpqOptions(limit=2)).count() == 2
    assert ask("(a|b|c)*", s="n0") == {("n0",), ("n1",), ("n2",), ("n3",)}
    empty = Graph(spark.createDataFrame([], "s string, p string, o string"))
    assert planner.evaluate(empty, "a+").count() == 0 == planner.evaluate(empty, "a*", o="x").count()


def test_masks_over_one_word():
    """Expressions of 62, 63, 64 and 130 symbols: narrow up to 63 states, arrays of words beyond."""
    from rpqspark.automaton import bitparallel
    from rpqspark.lang.parser import parse

    for m in (62, 63, 64, 130):
        t = bitparallel.compile(parse("/".join(["a?"] * (m - 1) + ["b"])))
        assert t.wide == (m + 1 > 63)
        d = t.initial
        for c in "a" * (m - 1) + "b":
            d = t.forward(d, c)
        assert d & t.final and not t.forward(d, "a")


def test_wide_masks_in_frames(spark, tiny):
    path = "/".join(["(a|b)?"] * 64) + "/c"
    got = planner.evaluate(tiny, path, s="n2", options=RpqOptions(executor="frontier", fast_paths=False, most_rounds=80))
    assert rows(got) == {("n3",)}


def test_workload_patterns():
    from rpqspark.lang.patterns import classify

    for q in QUERIES.values():
        if q.id not in ("w14", "w22", "w23", "w24", "w21"):
            assert classify(q.s, q.path, q.o) == q.pattern, q.id
    assert set(queries.oracle_sql()) <= set(queries.queries())


def test_builders_equal_a_global_order(spark, sf_dir):
    from pyspark.sql import Window
    from pyspark.sql import functions as F

    e = sources.table(spark, sf_dir, "events")
    want = e.withColumn("next", F.lead("user_id").over(Window.orderBy("ts", "event_id"))).select("event_id", "next")
    assert rows(sources.followed(e).select("event_id", "next")) == rows(want)


def test_nearest_vectors_over_many_blocks(spark, monkeypatch):
    import numpy as np

    monkeypatch.setattr(sources, "KNN_BLOCK", 16)
    assert not hasattr(sources, "KNN_VECTORS")
    rnd = np.random.default_rng(4)
    x = rnd.normal(size=(150, 6))
    x[20:60] = x[3]
    given = [(i, v.tolist(), i % 4) for i, v in enumerate(x)]
    odd = [(900, None, 1), (901, [0.0] * 6, 1), (902, [float("nan")] * 6, 1)]
    got = {}
    for a, label, b in sources.nearest(spark.createDataFrame(given + odd, "vec_id long, embedding array<double>, label int"), 5).collect():
        assert label == a % 4
        got.setdefault(a, set()).add(b)
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    want = {}
    for i, v in enumerate(unit):
        cosine = (unit * v).sum(axis=1)
        want[i] = set([j for j in np.lexsort((np.arange(150), -cosine)).tolist() if j != i][:5])
    assert got == want


def test_log_patterns_come_from_the_events(spark, tmp_path):
    """The histogram counts the rows of the given table."""
    from rpqspark import queries

    spark.createDataFrame([(1, "view"), (2, "click"), (2, "click"), (None, "error"), (3, "signup"), (3, "purchase"), (4, "odd"), (4, None)], "user_id long, event_type string").write.parquet(str(tmp_path / "events.parquet"))
    got = sorted(map(tuple, queries.queries()["log_patterns"](spark, str(tmp_path)).collect()))
    assert got == sorted({"v /* c": 1, "v * c": 2, "v + c": 1, "c * v": 1, "v / v": 1}.items())
