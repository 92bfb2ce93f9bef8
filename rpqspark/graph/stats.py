"""Graph statistics."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .model import Graph


def stats(g: Graph) -> DataFrame:
    """One row: edges, nodes, subjects, labels, objects."""
    e = g.edges.agg(F.count("*").alias("edges"), F.countDistinct("s").alias("subjects"), F.countDistinct("p").alias("labels"), F.countDistinct("o").alias("objects"))
    return e.crossJoin(g.nodes().agg(F.count("*").alias("nodes"))).select("edges", "nodes", "subjects", "labels", "objects")


def label_counts(g: Graph) -> DataFrame:
    """(p, n): cardinality of each label, from which the planner picks a direction."""
    return g.edges.groupBy("p").agg(F.count("*").alias("n"))


def distinct_in_range(g: Graph, approximate: bool = False) -> DataFrame:
    """(p, edges, sources, targets): selectivity of each label; sketches if approximate."""
    distinct = F.approx_count_distinct if approximate else F.countDistinct
    return g.edges.groupBy("p").agg(F.count("*").alias("edges"), distinct("s").alias("sources"), distinct("o").alias("targets"))


def labels_into(g: Graph, lo: str, hi: str) -> DataFrame:
    """(p, edges, targets): the labels that lead into a range of objects, both ends included."""
    rows = g.edges.filter((F.col("o") >= lo) & (F.col("o") <= hi))
    return rows.groupBy("p").agg(F.count("*").alias("edges"), F.countDistinct("o").alias("targets"))


def sources_of(g: Graph, names: list[str]) -> DataFrame:
    """One row (sources): distinct nodes that any of some labels leaves."""
    return g.edges.filter(F.col("p").isin(names)).agg(F.countDistinct("s").alias("sources"))
