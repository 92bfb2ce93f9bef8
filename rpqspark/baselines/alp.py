"""Operator by operator: concatenation joins sub-results, a closure is a node-wise
search over the sub-result from each start node."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..exec.fastpaths import edges_of
from ..graph.model import Graph
from ..lang.ast import Alt, Cat, Class, Eps, Expr, Opt, Plus, Star
from ..lang.parser import parse
from ..lang.rewrite import push_inverse
from .closure import semi_naive


def _walk(g: Graph, e: Expr) -> DataFrame:
    same = lambda: g.nodes().select(F.col("node").alias("s"), F.col("node").alias("o"))
    match e:
        case Eps():
            return same()
        case Class():
            return edges_of(g, e)
        case Cat(parts):
            join = lambda a, b: a.withColumnRenamed("o", "m").join(b.withColumnRenamed("s", "m"), "m").select("s", "o").distinct()
            return reduce(join, [_walk(g, p) for p in parts])
        case Alt(parts):
            return reduce(DataFrame.union, [_walk(g, p) for p in parts]).distinct()
        case Opt(b):
            return _walk(g, b).union(same()).distinct()
        case Plus(b):
            return semi_naive(_walk(g, b))
        case Star(b):
            return semi_naive(_walk(g, b)).union(same()).distinct()
    raise TypeError(e)


def evaluate(g: Graph, e: Expr | str, s: str | None = None, o: str | None = None) -> DataFrame:
    out = _walk(g, push_inverse(parse(e) if isinstance(e, str) else e))
    if s is not None:
        out = out.filter(F.col("s") == s)
    return out.filter(F.col("o") == o) if o is not None else out
