"""Tables of a running evaluation in the shared folder of ``spark.checkpoint.dir``.

Every round is one job that writes a small table; a written table cuts the lineage,
survives lost executors, and lets an evaluation resume from its last round.
"""

from __future__ import annotations

import uuid
import warnings

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; where it is unset, one in the warehouse, with a
    warning, since all executors must reach it."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        given = spark.sparkContext._jsc.sc().getCheckpointDir()
        root = given.get() if given.isDefined() else None
    if not root:
        root = f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/_rounds"
        warnings.warn(f"spark.checkpoint.dir is unset; intermediate tables go to {root}", stacklevel=3)
    return root.rstrip("/")


class Store:
    #: Stores of this process that were not dropped.
    live: list[Store] = []

    def __init__(self, spark: SparkSession, name: str):
        self.spark = spark
        self.root = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
        Store.live.append(self)

    def path(self, table: str) -> str:
        return f"{self.root}/{table}"

    def save(self, df: DataFrame, table: str) -> DataFrame:
        df.write.mode("overwrite").parquet(self.path(table))
        return self.spark.read.schema(df.schema).parquet(self.path(table))

    def rounds(self, schema, table: str) -> DataFrame:
        """All rounds that were saved under a table, as one."""
        return self.spark.read.schema(schema).option("recursiveFileLookup", "true").parquet(self.path(table))

    def drop(self) -> None:
        jvm = self.spark.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(self.root)
        p.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
        if self in Store.live:
            Store.live.remove(self)


def release(spark: SparkSession, keep: tuple[str, ...] = ("graph", "cyclic", "encode", "levels", "incremental")) -> int:
    """Deletes the tables of past evaluations, whose answers were read; stored graphs, indexes and running streams stay. Gives their number."""
    done = [s for s in Store.live if s.spark is spark and not s.root.rsplit("/", 1)[1].startswith(keep)]
    for s in done:
        s.drop()
    return len(done)
