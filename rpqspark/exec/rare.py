"""Split at a rare label: start at its edges, run both ways, join on the edge."""

from __future__ import annotations

import dataclasses

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..automaton import bitparallel
from ..automaton.bitparallel import Masks
from ..graph.model import Graph
from ..lang.ast import Cat, Class, Eps, sym
from ..lang.parser import parse
from ..lang.rewrite import push_inverse, simplify
from . import backward, kernel, keyed, reach
from .options import RpqOptions, RunStats


def split(path, label: str):
    """(before, after) of the one place where a top-level concatenation reads the label."""
    e = simplify(push_inverse(parse(path) if isinstance(path, str) else path))
    parts = e.parts if isinstance(e, Cat) else (e,)
    at = [i for i, p in enumerate(parts) if isinstance(p, Class) and p == sym(label)]
    if len(at) != 1:
        raise ValueError("the label must stand once in the top-level concatenation")
    join = lambda x: Eps() if not x else x[0] if len(x) == 1 else Cat(tuple(x))
    return join(parts[: at[0]]), join(parts[at[0] + 1 :])


def split_evaluate(g: Graph, path, label: str, options: RpqOptions = RpqOptions(), stats: RunStats | None = None) -> DataFrame:
    """(s, o) of all answers.

    If all edges of the path fit the kernel, what the rare edges reach both ways is searched once for all of
    them, and its answers come by sets of ends. Else backward from the subjects of the rare edges, each on its own; then forward from the objects,
    those that one start has reached together, as two starts share few answers but many rare edges. A
    half whose edges fit the kernel goes by it, else by the frontier: the rounds of a half are as many as its longest path.
    """
    before, after = split(path, label)
    whole = bitparallel.compile(simplify(push_inverse(parse(path) if isinstance(path, str) else path)))
    if not (whole.wide or whole._negated or whole.nfa.arrive):
        rows = kernel.fetch(g, sorted({n for n, _ in whole.B}), options.kernel_edges)
        if rows is not None:
            return reach.pairs(g.spark, rows, whole, whole.label(label))
    rare = g.edges.filter(F.col("p") == label).select(F.col("s").alias("a"), F.col("o").alias("b"))

    def half(e):
        t = bitparallel.compile(e)
        return t, None if t.wide or t._negated or t.nfa.arrive else kernel.fetch(g, sorted({n for n, _ in t.B}), options.kernel_edges)

    t, rows = half(before)
    begins = rare.select(F.col("a").alias("node")).distinct()
    if not t.nfa.mask(t.nfa.last):
        starts = rare.select(F.col("a").alias("s"), "b")
    else:
        left = keyed.from_each(g, before, begins, False, dataclasses.replace(options, executor="frontier" if rows is None else "auto", limit=None))
        # The size of what a search gives is not known before; only the rare edges, which are counted, may be sent.
        few = g.is_stored and g.counts().get(label, 0) <= options.broadcast_rows
        left = left.select(F.col("origin").alias("a"), F.col("node").alias("s"))
        starts = (left.join(F.broadcast(rare), "a") if few else left.hint("merge").join(rare, "a")).select("s", "b").distinct()
    t, rows = half(after)
    masks, last = Masks(t), t.nfa.mask(t.nfa.last)
    if not last:
        return starts.select("s", F.col("b").alias("o")).distinct()
    if rows is not None:
        together = starts.select(F.col("s").alias("node"), F.col("b").alias("at")).repartition("node").sortWithinPartitions("node")
        found = kernel.evaluate_local(g.spark, rows, t, together, False).select(F.col("origin").alias("s"), F.col("node").alias("o"))
    else:
        seeds = starts.select(F.col("s").alias("k"), F.col("b").alias("node"), masks.lit(t.initial).alias("mask"))
        seen = backward.traverse(g, t, seeds, ["k"], False, dataclasses.replace(options, limit=None), stats)
        found = seen.filter(masks.some(masks.both(F.col("mask"), masks.lit(last)))).select(F.col("k").alias("s"), F.col("node").alias("o"))
    return found.union(starts.select("s", "b")).distinct() if t.nfa.nullable else found
