"""One backward run per object, all in one frame with the object as a key, unpruned."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..automaton import bitparallel
from ..automaton.bitparallel import Masks
from ..exec import backward
from ..exec.options import RpqOptions, RunStats
from ..graph.model import Graph
from ..lang.ast import Expr
from ..lang.parser import parse


def evaluate(g: Graph, e: Expr | str, stats: RunStats | None = None, o: str | None = None) -> DataFrame:
    """(s, o) pairs; with a constant object, of that one run only."""
    t = bitparallel.compile(parse(e) if isinstance(e, str) else e)
    masks = Masks(t)
    nodes = g.nodes() if o is None else g.nodes().filter(F.col("node") == o)
    seeds = nodes.select(F.col("node").alias("origin"), "node", masks.lit(t.nfa.mask(t.nfa.last)).alias("mask"))
    seen = backward.traverse(g, t, seeds, ["origin"], True, RpqOptions(), stats)
    out = seen.filter(masks.some(masks.both(F.col("mask"), masks.lit(t.initial)))).select(F.col("node").alias("s"), F.col("origin").alias("o"))
    return out.union(nodes.select(F.col("node").alias("s"), F.col("node").alias("o"))).distinct() if t.nfa.nullable else out
