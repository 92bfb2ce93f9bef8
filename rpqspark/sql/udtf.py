"""Table and scalar functions over paths."""

from __future__ import annotations

import functools

from pyspark.sql import SparkSession
from pyspark.sql.functions import udf, udtf
from pyspark.sql.types import BooleanType, IntegerType, StringType, StructType

from ..automaton import position
from ..lang.parser import parse


# Types are objects, not text: text would need a session at import.
@udtf(returnType=StructType().add("position", IntegerType()).add("label", StringType()).add("inverse", BooleanType()).add("first", BooleanType()).add("last", BooleanType()))
class RpqParse:
    """Positions of a path and their labels."""

    def eval(self, path: str):
        n = position.build(parse(path))
        for q, c in enumerate(n.positions, 1):
            for name, inverse in sorted(c.labels):
                yield q, name, inverse, q in n.first, q in n.last


@udtf(returnType=StructType().add("state", IntegerType()).add("label", StringType()).add("inverse", BooleanType()).add("target", IntegerType()))
class RpqTransitions:
    """Transitions of a path's automaton; state 0 is the initial one."""

    def eval(self, path: str):
        n = position.build(parse(path))
        for q in range(n.m + 1):
            for t in sorted(n.after(q)):
                for name, inverse in sorted(n.positions[t - 1].labels):
                    yield q, name, inverse, t


@udtf(returnType=StructType().add("s", StringType()).add("o", StringType()))
class RpqLocal:
    """Answers on a tiny graph that a row carries, as arrays of sources, labels and targets."""

    def eval(self, s: list, p: list, o: list, path: str):
        n = _automaton(path)
        edges = list(zip(s or (), p or (), o or ()))
        for x in sorted({v for a, _, b in edges for v in (a, b)}):
            seen, todo = {(x, 0)}, [(x, 0)]
            while todo:
                v, q = todo.pop()
                for a, label, b in edges:
                    for inverse, at, to in ((False, a, b), (True, b, a)):
                        if at == v:
                            for t in n.after(q) & n.targets(label, inverse):
                                if (to, t) not in seen:
                                    seen.add((to, t))
                                    todo.append((to, t))
            hit = {v for v, q in seen if q in n.last} | ({x} if n.nullable else set())
            for v in sorted(hit):
                yield x, v


@functools.lru_cache(256)
def _automaton(path: str) -> position.PositionNFA:
    return position.build(parse(path))


@udf(BooleanType(), useArrow=True)
def rpq_accepts(word, path):
    """Whether a list of forward labels spells a word of the path."""
    if word is None or path is None:
        return None
    return _automaton(path).accepts([(w, False) for w in word])


def register(spark: SparkSession) -> None:
    spark.udtf.register("rpq_parse", RpqParse)
    spark.udtf.register("rpq_transitions", RpqTransitions)
    spark.udtf.register("rpq_local", RpqLocal)
    spark.udf.register("rpq_accepts", rpq_accepts)
