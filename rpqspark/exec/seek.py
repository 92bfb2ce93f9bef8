"""The smallest binding of a variable at or after a bound that has a solution."""

from __future__ import annotations

import bisect

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..automaton import bitparallel
from ..graph.model import Graph
from ..lang import rewrite
from ..lang.parser import parse
from . import planner, ring
from .options import RpqOptions


def next_solution(g: Graph, path: str, var: str, lower: str, s: str | None = None, o: str | None = None, options: RpqOptions = RpqOptions()) -> DataFrame:
    """One row (value): the least name >= lower that ``var`` (s or o) takes; null if none.

    A run from the whole range of starts gives all bindings at once, without an
    origin column; the least of them is an aggregate. On the index (executor "ring", the
    other end constant) ranges of bindings are halved instead, and no answer but one is made; a graph over one shard is searched as by the planner.
    """
    if options.executor == "ring" and ring.fits(g, options.kernel_edges):
        # Bisection of ranges of bindings: a range either holds one or is left as a whole.
        shard, e = ring.shard_of(g, options.kernel_edges), rewrite.push_inverse(parse(path))
        tables, mirrored = bitparallel.compile(e), bitparallel.compile(rewrite.reverse(e))
        tables, mirrored, goal = (tables, mirrored, o) if var == "s" else (mirrored, tables, s)
        at = {x: i for i, x in enumerate(shard.names)}
        first = ring.next_subject(shard, tables, mirrored, bisect.bisect_left(shard.names, lower), at[goal]) if goal in at else None
        return g.spark.createDataFrame([(None if first is None else shard.names[first],)], "value string")
    out = planner.evaluate(g, path, s, o, options)
    return out.filter(F.col(var) >= lower).agg(F.min(var).alias("value"))
