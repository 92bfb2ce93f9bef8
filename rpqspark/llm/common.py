"""Shared plumbing: table reading, staged tables in the shared folder, batches."""

from __future__ import annotations

import uuid
import warnings

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

#: Rows of one Arrow batch at most; whole texts travel in them, so that it is small.
BATCH_ROWS = 512


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def small_batches(spark: SparkSession, rows: int = BATCH_ROWS) -> None:
    """Bound the memory of a Python worker: a batch holds ``rows`` texts at most.

    The session's setting is changed and stays so, as results are lazy and a batch is made
    when they are read; callers with needs of their own set it before they read.
    """
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) != rows:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(rows))


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def columns(df: DataFrame, names: list[str]) -> DataFrame:
    """Only the named columns; other columns, whatever their names, are left out."""
    return df.select(*[df[f"`{n}`"] for n in names])


class Stage:
    """Tables of intermediate rows in the shared folder of ``spark.checkpoint.dir``.

    A written table cuts the lineage and survives lost executors. ``drop``
    deletes one that nothing reads any more.
    """

    def __init__(self, spark: SparkSession, name: str):
        self.spark, root = spark, spark.conf.get("spark.checkpoint.dir", None)
        if not root:
            given = spark.sparkContext._jsc.sc().getCheckpointDir()
            root = given.get() if given.isDefined() else None
        if not root:
            root = f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/_stages"
            warnings.warn(f"spark.checkpoint.dir is unset; intermediate tables go to {root}", stacklevel=2)
        self.root = f"{root.rstrip('/')}/{name}-{uuid.uuid4().hex}"

    def save(self, df: DataFrame, table: str) -> DataFrame:
        path = f"{self.root}/{table}"
        df.write.mode("overwrite").option("compression", "zstd").parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, table: str) -> None:
        jvm = self.spark.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path(f"{self.root}/{table}")
        path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)

    def release(self) -> None:
        """Let Spark's cleaner see that the shuffles of saved tables are done with."""
        import gc

        gc.collect()
        self.spark.sparkContext._jvm.System.gc()


def batch(schema: pa.Schema, *arrays) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([a if isinstance(a, pa.Array) else pa.array(a, f.type) for a, f in zip(arrays, schema)], schema=schema)
