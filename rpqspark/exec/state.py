"""Traversal state shared by all frontier executors.

``moves`` is the pruned edge table as seen by the traversal: (at, to, b), where a
step leads from ``at`` to ``to`` and b is the mask of states that its label enters.
``frontier`` and ``visited`` hold (keys..., node, mask); a frontier has only states that
its node never had before, so each product node enters a frontier once.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..automaton.bitparallel import Masks
from ..graph.model import Graph


def moves(g: Graph, masks: Masks, backward: bool, label_pruning: bool = True) -> DataFrame:
    """Steps of the labels that the expression reads, in the direction of travel.

    Inverse labels read the same edges from the other end; the completed graph is
    never written out.
    """
    labels = masks.label_frame(g.spark, g.labels() if masks.tables._negated or not label_pruning else [])
    used = masks.tables.used(g.labels() if masks.tables._negated else [])
    one_way = lambda inverse: [n for (n, i) in used if i is inverse]
    parts = []
    for inverse in (False, True):
        names = one_way(inverse)
        if not names:
            continue
        # Backward along p: from the object to the subject; an inverse label turns that round.
        at, to = ("o", "s") if backward != inverse else ("s", "o")
        edges = g.edges.filter(F.col("p").isin(names)) if label_pruning else g.edges
        b = F.broadcast(labels.filter(F.col("inverse") == inverse).select("p", "b"))
        parts.append(edges.join(b, "p").select(F.col(at).alias("at"), F.col(to).alias("to"), "b"))
    if not parts:
        return g.spark.createDataFrame([], f"at string, to string, b {masks.type}")
    return parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])


def step(frontier: DataFrame, edges: DataFrame, masks: Masks, keys: list[str], backward: bool, merge: bool = True) -> DataFrame:
    """Candidates (keys, node, mask) of one step; states of one node are merged."""
    met = frontier.withColumnRenamed("node", "at").join(edges, "at")
    if backward:
        x = masks.both(F.col("mask"), F.col("b"))
        met = met.withColumn("x", x).filter(masks.some(F.col("x"))).withColumn("mask", masks.step(F.col("x"), True))
    else:
        met = met.withColumn("mask", masks.both(masks.step(F.col("mask"), False), F.col("b")))
    met = met.filter(masks.some(F.col("mask"))).select(*keys, F.col("to").alias("node"), "mask")
    return merged(met, masks, keys) if merge else met


def merged(rows: DataFrame, masks: Masks, keys: list[str]) -> DataFrame:
    """One row per node with the union of its states; combined before the shuffle."""
    return rows.groupBy(*keys, "node").agg(masks.either("mask").alias("mask"))


def fresh(candidates: DataFrame, visited: DataFrame, masks: Masks, keys: list[str]) -> DataFrame:
    """States that their node did not have: mask and not seen."""
    seen = merged(visited, masks, keys).withColumnRenamed("mask", "seen")
    rows = candidates.join(seen, [*keys, "node"], "left")
    left = F.when(F.col("seen").isNull(), F.col("mask")).otherwise(masks.without(F.col("mask"), F.col("seen")))
    return rows.withColumn("mask", left).filter(masks.some(F.col("mask"))).select(*keys, "node", "mask")
