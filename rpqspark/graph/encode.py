"""Dictionary encoding without a single-partition window.

Names are sorted by range partitions; a partition's first number is the count of all
before it, summed over per-partition counts (one small row each).
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..exec.store import Store
from .model import Graph


def numbered(df: DataFrame, order: list[str], name: str, store: Store, table: str, start: int = 1) -> DataFrame:
    """df with a gapless number in the order of the given columns."""
    spark = df.sparkSession
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    parts = store.save(df.repartitionByRange(n, *order).withColumn("_part", F.spark_partition_id()), table)
    counts = parts.groupBy("_part").count()
    before = counts.select("_part", (F.sum("count").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1))).alias("_before"))
    rank = F.row_number().over(Window.partitionBy("_part").orderBy(*order))
    return parts.withColumn("_rank", rank).join(F.broadcast(before), "_part").withColumn(name, (F.col("_rank") + F.coalesce("_before", F.lit(0)) + (start - 1)).cast("long")).drop("_part", "_rank", "_before")


def running(df: DataFrame, order: list[str], value: str, name: str, store: Store, table: str) -> DataFrame:
    """df with the sum of a column over all rows before, in the order of the given columns."""
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    parts = store.save(df.repartitionByRange(n, *order).withColumn("_part", F.spark_partition_id()), table)
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    base = parts.groupBy("_part").agg(F.sum(value).alias("_t")).select("_part", F.coalesce(F.sum("_t").over(before), F.lit(0)).alias("_base"))
    inside = F.coalesce(F.sum(value).over(Window.partitionBy("_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return parts.withColumn("_inside", inside).join(F.broadcast(base), "_part").withColumn(name, (F.col("_base") + F.col("_inside")).cast("long")).drop("_part", "_inside", "_base")


@dataclass
class Encoded:
    """Edges (s, p, o) as numbers, and both dictionaries (id, name)."""

    edges: DataFrame
    nodes: DataFrame
    labels: DataFrame

    def decode(self, df: DataFrame, *names: str) -> DataFrame:
        """Node numbers of the named columns to their names."""
        for c in names:
            back = self.nodes.select(F.col("id").alias(c), F.col("name").alias(f"_{c}"))
            df = df.join(back, c).drop(c).withColumnRenamed(f"_{c}", c)
        return df

    def n_labels(self) -> int:
        return self.labels.count()


def encode(g: Graph) -> Encoded:
    store = Store(g.spark, "encode")
    nodes = store.save(numbered(g.nodes().withColumnRenamed("node", "name"), ["name"], "id", store, "node_parts"), "nodes").select("id", "name")
    labels = store.save(g.edges.select(F.col("p").alias("name")).distinct().withColumn("id", F.row_number().over(Window.orderBy("name")).cast("int")), "labels").select("id", "name")
    e = g.edges.join(F.broadcast(labels.select(F.col("id").alias("_p"), F.col("name").alias("p"))), "p")
    e = e.join(nodes.select(F.col("id").alias("_s"), F.col("name").alias("s")), "s").join(nodes.select(F.col("id").alias("_o"), F.col("name").alias("o")), "o")
    return Encoded(store.save(e.select(F.col("_s").alias("s"), F.col("_p").alias("p"), F.col("_o").alias("o")), "edges"), nodes, labels)


def inverse_id(p, n_labels: int):
    """The number of an inverse label: p + |P|, and back."""
    return p + n_labels if p <= n_labels else p - n_labels


def complete(edges: DataFrame, n_labels: int) -> DataFrame:
    """Encoded edges and their inverses."""
    return edges.unionByName(edges.select(F.col("o").alias("s"), (F.col("p") + n_labels).cast("int").alias("p"), F.col("s").alias("o")))
