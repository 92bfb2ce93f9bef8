"""Streams: late rows, state across batches, and incremental answers."""

import shutil

import pandas as pd

from rpqspark import queries
from rpqspark.exec import planner
from rpqspark.exec.options import RpqOptions
from rpqspark.graph.model import Graph
from rpqspark.stream import events as stream
from rpqspark.stream.incremental import Incremental

SCHEMA = "event_id long, ts timestamp, user_id long, event_type string"


def feed(spark, path, batches):
    for k, rows in enumerate(batches):
        df = spark.createDataFrame([(i, pd.Timestamp(t).to_pydatetime(), u, e) for i, t, u, e in rows], SCHEMA)
        df.coalesce(1).write.mode("append").parquet(str(path))


def run(spark, df, tmp_path, name):
    q = df.writeStream.format("memory").queryName(name).outputMode("append").option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name).collect(), q


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    batches = [[(1, "2024-01-01 10:00", 1, "click")], [(2, "2024-01-02 10:00", 1, "click")], [(3, "2024-01-01 11:00", 1, "click"), (4, "2024-01-04 00:00", 1, "click")], [(5, "2024-01-09 00:00", 1, "click")]]
    feed(spark, tmp_path / "in", batches)
    rows, q = run(spark, stream.windowed(stream.source(spark, str(tmp_path / "in"), SCHEMA)), tmp_path, "late")
    n = {str(r.start.date()): r.n for r in rows}
    dropped = sum(op["numRowsDroppedByWatermark"] for p in q.recentProgress for op in p["stateOperators"])
    assert n["2024-01-01"] + dropped == 2 and n["2024-01-02"] == 1


def test_state_goes_on_over_batches(spark, tmp_path):
    feed(spark, tmp_path / "m", [[(1, "2024-01-01 10:00", 1, "click"), (2, "2024-01-01 10:01", 2, "purchase")], [(3, "2024-01-01 10:02", 1, "view")], [(4, "2024-01-01 10:03", 1, "purchase"), (5, "2024-01-01 10:04", 2, "click")]])
    rows, _ = run(spark, stream.matches(stream.source(spark, str(tmp_path / "m"), SCHEMA), "click/view*/purchase"), tmp_path, "matched")
    assert [(r.user_id, r.event_id) for r in rows] == [(1, 4)]
    shutil.rmtree(tmp_path / "m")


def test_incremental_equals_batch(spark):
    edges = [("n0", "a", "n1"), ("n1", "b", "n2"), ("n2", "a", "n0"), ("n3", "a", "n1"), ("n4", "b", "n3"), ("n5", "a", "n4")]
    frame = lambda rows: spark.createDataFrame(rows, "s string, p string, o string").coalesce(1)
    i = Incremental(Graph(frame(edges[:2])), "(a|b)*/b", "n2")
    for k in (2, 4):
        i.add(frame(edges[k : k + 2]))
        want = planner.evaluate(Graph(frame(edges[: k + 2])), "(a|b)*/b", o="n2", options=RpqOptions(executor="kernel"))
        assert {r.s for r in i.answers().collect()} == {r.s for r in want.collect()}


def test_contract(spark, sf_dir):
    import __spark_entry__ as entry

    assert entry.entry(spark).columns == ["s", "o"] and entry.entry(spark).limit(1).count() == 1
    assert set(queries.queries()) <= set(entry.queries())
