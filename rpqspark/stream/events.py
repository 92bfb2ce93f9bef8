"""Streams of events: windows, duplicates, joins, and automata over users' events.

Every function takes a streaming or a batch DataFrame of events; ``ts`` becomes a
TIMESTAMP first, since watermarks ask for one.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..automaton import bitparallel
from ..lang.parser import parse


def source(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    return timed(spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path))


def timed(events: DataFrame) -> DataFrame:
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def windowed(events: DataFrame, length: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(start, event_type, n): edges per label and window; later rows than ``late`` are dropped."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.withWatermark("ts", late).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """(user_id, start, end, n): bursts of a user's events."""
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    events = events.withWatermark("ts", late)
    return events.dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else events.dropDuplicates(["event_id"])


def purchases_after_clicks(events: DataFrame, within: str = "1 hour") -> DataFrame:
    """(user_id, click, purchase): pairs of a user's click and purchase within an interval."""
    c = events.filter("event_type = 'click'").select("user_id", F.col("event_id").alias("click"), F.col("ts").alias("t1")).withWatermark("t1", within)
    p = events.filter("event_type = 'purchase'").select(F.col("user_id").alias("u"), F.col("event_id").alias("purchase"), F.col("ts").alias("t2")).withWatermark("t2", within)
    return c.join(p, F.expr(f"user_id = u AND t2 >= t1 AND t2 <= t1 + INTERVAL {within}")).select("user_id", "click", "purchase")


def labelled(events: DataFrame, labels: DataFrame) -> DataFrame:
    """Stream with static: events with the number of their label, labels (name, id)."""
    return events.join(F.broadcast(labels), events.event_type == labels.name).select("event_id", "user_id", "id")


def matches(events: DataFrame, path: str) -> DataFrame:
    """(user_id, event_id): events at which a user's events so far, from some event on, spell a
    word of the path. State: one mask per user; events of a batch are taken in time order."""
    tables = bitparallel.compile(parse(path))

    def work(key, pdfs, state):
        mask = state.get[0] if state.exists else 0
        rows = pd.concat(list(pdfs)).sort_values(["ts", "event_id"])
        out = []
        for event, kind in zip(rows["event_id"], rows["event_type"]):
            mask = tables.forward(mask | tables.initial, kind)
            if mask & tables.final & ~tables.initial:
                out.append(event)
        state.update((mask,))
        yield pd.DataFrame({"user_id": [key[0]] * len(out), "event_id": out}, dtype="int64")

    return events.groupBy("user_id").applyInPandasWithState(work, "user_id long, event_id long", "mask long", "append", "NoTimeout")
