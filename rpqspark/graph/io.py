"""Triples in and out of files, and tables clustered for traversal."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .model import Graph, validate_triples


def read_triples(spark: SparkSession, path: str, format: str = "parquet", cols: tuple[str, str, str] = ("s", "p", "o")) -> Graph:
    """A graph from parquet, orc, json or csv files with the named columns."""
    reader = spark.read.option("header", "true") if format == "csv" else spark.read
    df = reader.format(format).load(path)
    return Graph.of(df.select(*[F.col(f"`{c}`").alias(n) for c, n in zip(cols, "spo")]))


def read_nt(spark: SparkSession, path: str) -> Graph:
    """A graph from lines such as ``<s> <p> <o> .`` with names or quoted literals."""
    line = r'^\s*<([^>]*)>\s+<([^>]*)>\s+(?:<([^>]*)>|"((?:[^"\\]|\\.)*)"\S*)\s*\.\s*$'
    t = spark.read.text(path).filter(F.col("value").rlike(line))
    part = lambda i: F.regexp_extract("value", line, i)
    return Graph.of(t.select(part(1).alias("s"), part(2).alias("p"), F.when(part(3) != "", part(3)).otherwise(part(4)).alias("o")))


def write_clustered(g: Graph, path: str, by: str = "dst", files: int = 8, hot_labels: int = 64) -> None:
    """One clustering of the edges: frequent labels each in a folder, rare ones hashed
    together, sorted by the end that a traversal starts from. Two clusterings of one
    table (by object and by subject) stand in for storing inverse edges."""
    at = "o" if by == "dst" else "s"
    counts = g.edges.groupBy("p").count()
    top = F.broadcast(counts.orderBy(F.desc("count"), "p").limit(hot_labels).select("p", F.col("p").alias("_hot")))
    e = g.edges.join(top, "p", "left").withColumn("p_group", F.coalesce(F.col("_hot"), F.concat(F.lit("rare_"), F.pmod(F.xxhash64("p"), F.lit(16)).cast("string")))).drop("_hot")
    e.repartitionByRange(files, "p_group", at).sortWithinPartitions("p_group", "p", at).write.mode("overwrite").partitionBy("p_group").parquet(path)


def read_clustered(spark: SparkSession, path: str, labels: list[str] | None = None) -> Graph:
    """A clustered table; with labels, only their folders and the rare ones are read."""
    df = spark.read.parquet(path)
    if labels is not None:
        df = df.filter((F.col("p_group").isin(labels) | F.col("p_group").startswith("rare_")) & F.col("p").isin(labels))
    return Graph(df.select("s", "p", "o"))


def write_result(df: DataFrame, path: str, format: str = "parquet") -> None:
    df.write.mode("overwrite").format(format).option("header", "true").save(path)


def register_graph(g: Graph, name: str) -> None:
    validate_triples(g.edges)
    g.edges.createOrReplaceTempView(name)
