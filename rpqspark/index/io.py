"""Saved indexes: Parquet tables beside a small table of counts."""

from __future__ import annotations

from pyspark.sql import SparkSession

from .cyclic import CyclicIndex


def save(index: CyclicIndex, path: str) -> None:
    for c, df in index.columns.items():
        df.repartitionByRange("pos").sortWithinPartitions("pos").write.mode("overwrite").parquet(f"{path}/column_{c}")
        index.starts[c].write.mode("overwrite").parquet(f"{path}/starts_{c}")
    spark = next(iter(index.columns.values())).sparkSession
    spark.createDataFrame([(index.n, "".join(index.columns))], "n long, columns string").coalesce(1).write.mode("overwrite").json(f"{path}/manifest")


def load(spark: SparkSession, path: str) -> CyclicIndex:
    m = spark.read.schema("n long, columns string").json(f"{path}/manifest").first()
    return CyclicIndex({c: spark.read.parquet(f"{path}/column_{c}") for c in m["columns"]}, {c: spark.read.parquet(f"{path}/starts_{c}") for c in m["columns"]}, m.n)
