"""Sizes and work counters of evaluations."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..baselines import product
from ..exec import planner
from ..exec.options import RpqOptions, RunStats
from ..graph.model import Graph
from ..lang.parser import parse


def product_size(g: Graph, path: str, s: str | None = None, o: str | None = None) -> DataFrame:
    """One row: nodes and edges of the product subgraph that the fixed end induces, and
    the length of its longest breadth-first level. From a fixed object the product of the
    graph and the path's own automaton is walked backward, so that each state of a node counts."""
    e, back = parse(path), o is not None
    const = o if back else s
    source = g.spark.createDataFrame([(const,)], "node string") if const is not None else None
    seen, _, rounds = product.reached(g, e, source, backward=back)
    steps = product.materialise(g, e)
    steps = product.turned(steps) if back else steps
    edges = seen.join(steps, ["node", "state"]).agg(F.count("*").alias("product_edges"))
    return seen.agg(F.count("*").alias("product_nodes")).crossJoin(edges).withColumn("levels", F.lit(rounds).cast("long"))


def counters(g: Graph, path: str, s: str | None = None, o: str | None = None, **options) -> tuple[DataFrame, RunStats]:
    """One row of counters of a frontier run."""
    stats = RunStats()
    out = planner.evaluate(g, path, s, o, RpqOptions(executor="frontier", fast_paths=False, **options), stats=stats)
    n = out.count()
    row = [(stats.rounds, stats.frontier_rows, stats.states, stats.labels_read, n)]
    return g.spark.createDataFrame(row, "rounds long, visits long, states long, labels_read long, answers long"), stats
