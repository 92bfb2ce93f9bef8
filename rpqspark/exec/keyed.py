"""Runs from many given ends at once, keyed by the end."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..automaton import bitparallel
from ..automaton.bitparallel import Masks
from ..graph.model import Graph
from ..lang.ast import Expr
from ..lang.parser import parse
from . import backward, kernel
from .options import RpqOptions


def from_each(g: Graph, path: str | Expr, ends: DataFrame, forward: bool, options: RpqOptions = RpqOptions()) -> DataFrame:
    """(origin, node) of every answer whose one end is among ``ends`` (node); forward: as subjects."""
    t = bitparallel.compile(parse(path) if isinstance(path, str) else path)
    masks = Masks(t)
    ends = ends.select("node").distinct().join(g.nodes(), "node", "left_semi")
    rows = kernel.fetch(g, sorted({n for n, _ in t.B}), options.kernel_edges) if options.executor != "frontier" and not t._negated and not t.wide else None
    arrive = {t.nfa.bit(q): n for q, n in t.nfa.arrive.items()}
    if rows is not None:
        found = kernel.evaluate_local(g.spark, rows, t, ends, not forward, arrive)
    else:
        start, goal = (t.initial, t.nfa.mask(t.nfa.last)) if forward else (t.nfa.mask(t.nfa.last), t.initial)
        seeds = ends.select(F.col("node").alias("origin"), "node", masks.lit(start).alias("mask"))
        seen = backward.traverse(g, t, seeds, ["origin"], not forward, options, arrive=arrive)
        found = seen.filter(masks.some(masks.both(F.col("mask"), masks.lit(goal)))).select("origin", "node")
    return found.union(ends.select(F.col("node").alias("origin"), "node")).distinct() if t.nfa.nullable else found
