"""A recursive SQL query. Recursion only appends, so it needs a bound on the depth, and the
duplicates go at the end. The bound is doubled until the deepest level brings no new state
of a node; a search that needs more than Spark's own limits of recursion raises."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..exec.store import Store
from ..graph.model import Graph
from ..lang.parser import parse
from .product import transitions


def evaluate(g: Graph, path: str, s: str, max_depth: int | None = None, first_depth: int = 4) -> DataFrame:
    """(o): all ends of paths from a constant. ``max_depth``: raises where longer paths bring more."""
    rows, start, finals = transitions(g, parse(path))
    spark, depth = g.spark, min(first_depth, max_depth or first_depth)
    g.edges.createOrReplaceTempView("rcte_edges")
    spark.createDataFrame(rows, "q int, p string, inverse boolean, r int").createOrReplaceTempView("rcte_moves")
    g.nodes().createOrReplaceTempView("rcte_nodes")
    store = Store(spark, "recursive")
    while True:
        reached = store.save(spark.sql(f"""
            WITH RECURSIVE step AS (
                SELECT DISTINCT m.q, m.r, CASE WHEN m.inverse THEN e.o ELSE e.s END AS x, CASE WHEN m.inverse THEN e.s ELSE e.o END AS y
                FROM rcte_edges e JOIN rcte_moves m ON e.p = m.p
            ), reach(node, q, depth) AS (
                SELECT node, {start}, 0 FROM rcte_nodes WHERE node = :s
                UNION ALL
                SELECT step.y, step.r, reach.depth + 1 FROM reach JOIN step ON reach.node = step.x AND reach.q = step.q WHERE reach.depth < {int(depth)}
            )
            SELECT node, q, min(depth) AS depth FROM reach GROUP BY node, q""", args={"s": s}), f"depth{depth}")
        # No state that is first met at the bound: nothing lies beyond it.
        if not reached.filter(F.col("depth") >= depth).limit(1).count():
            return reached.filter(F.col("q").isin(*finals)).select(F.col("node").alias("o")).distinct()
        if max_depth is not None and depth >= max_depth:
            raise ValueError(f"paths of more than {max_depth} steps bring more answers")
        depth = depth * 2 if max_depth is None else min(depth * 2, max_depth)
