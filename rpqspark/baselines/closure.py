"""Transitive closure of a binary relation (s, o) by iterated joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..exec.store import Store


def semi_naive(rel: DataFrame) -> DataFrame:
    """One step longer in each round; only new pairs are extended."""
    store = Store(rel.sparkSession, "closure")
    rel = store.save(rel.select("s", "o").distinct(), "rel")
    front = store.save(rel, "rounds/0")
    k = 0
    while front.limit(1).count():
        k += 1
        longer = front.join(rel.select(F.col("s").alias("o"), F.col("o").alias("n")), "o").select("s", F.col("n").alias("o")).distinct()
        front = store.save(longer.join(store.rounds(rel.schema, "rounds"), ["s", "o"], "left_anti"), f"rounds/{k}")
    return store.rounds(rel.schema, "rounds")


def squaring(rel: DataFrame) -> DataFrame:
    """Path lengths double in each round."""
    store = Store(rel.sparkSession, "closure")
    now, k, n = store.save(rel.select("s", "o").distinct(), "r0"), 0, -1
    while (m := now.count()) != n:
        n, k = m, k + 1
        twice = now.join(now.select(F.col("s").alias("o"), F.col("o").alias("n")), "o").select("s", F.col("n").alias("o"))
        now = store.save(now.union(twice).distinct(), f"r{k}")
    return now
