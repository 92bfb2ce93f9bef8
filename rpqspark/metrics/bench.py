"""Query times of a log: averages, medians, timeouts, winners."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def summarise(runs: DataFrame, limit_s: float = 60.0) -> DataFrame:
    """runs (query, pattern, method, seconds) to one row per (method, kind of ends, pattern)
    and their totals: average, quartiles, timeouts. Times are cut at the limit."""
    kind = F.when(F.col("pattern").startswith("v") & F.col("pattern").endswith("v"), "both variable").otherwise("one constant")
    t = runs.withColumn("seconds", F.least("seconds", F.lit(limit_s))).withColumn("ends", kind)
    q = lambda p: F.percentile("seconds", F.lit(p))
    return t.rollup("method", "ends", "pattern").agg(F.count("*").alias("queries"), F.avg("seconds").alias("average"), q(0.25).alias("lower"), q(0.5).alias("median"), q(0.75).alias("upper"), F.count_if(F.col("seconds") >= limit_s).alias("timeouts")).filter("method IS NOT NULL")


def winners(runs: DataFrame) -> DataFrame:
    """(pattern, method, average, share): the fastest method of each pattern and the
    pattern's share of the log."""
    avg = runs.groupBy("pattern", "method").agg(F.avg("seconds").alias("average"), F.countDistinct("query").alias("n"))
    best = avg.withColumn("place", F.row_number().over(Window.partitionBy("pattern").orderBy("average", "method"))).filter("place = 1")
    total = runs.agg(F.countDistinct("query").alias("total"))
    return best.crossJoin(total).select("pattern", "method", "average", (F.col("n") / F.col("total")).alias("share"))


def table(runs: DataFrame) -> DataFrame:
    """(measure, one column per method): average, median and timeouts side by side."""
    s = runs.groupBy("method").agg(F.avg("seconds").alias("average"), F.percentile("seconds", F.lit(0.5)).alias("median"), F.count_if(F.col("seconds") >= 60).cast("double").alias("timeouts"))
    long = s.unpivot(["method"], ["average", "median", "timeouts"], "measure", "value")
    return long.groupBy("measure").pivot("method").agg(F.first("value"))
