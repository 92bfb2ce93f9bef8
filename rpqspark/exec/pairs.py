"""Both ends open: useful origins from one run over the whole node range, then their runs."""

from __future__ import annotations

import dataclasses

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..automaton.bitparallel import Masks, Tables
from ..graph.model import Graph
from . import backward, state
from .options import RpqOptions, RunStats


def phase_one(g: Graph, tables: Tables, options: RpqOptions, stats: RunStats | None = None, arrive=None, ends: DataFrame | None = None, marks: DataFrame | None = None) -> DataFrame:
    """(node, mask): the states from which some end is reached, without an origin column.

    All nodes (or ``ends``) start at once in the final states.
    """
    masks = Masks(tables)
    seeds = backward.seeds_of(g, masks, ends if ends is not None else g.nodes(), tables.nfa.mask(tables.nfa.last))
    return backward.traverse(g, tables, seeds, [], True, dataclasses.replace(options, limit=None), stats, arrive=arrive, premarked=marks)


def useful_sources(g: Graph, tables: Tables, options: RpqOptions, stats: RunStats | None = None) -> DataFrame:
    """(node): subjects that have an answer by a path of one step or more."""
    masks = Masks(tables)
    seen = phase_one(g, tables, options, stats)
    return seen.filter(masks.some(masks.both(F.col("mask"), masks.lit(tables.initial)))).select("node")


def evaluate(g: Graph, tables: Tables, reversed_tables: Tables, options: RpqOptions, stats: RunStats | None = None, arrive=None, marks: DataFrame | None = None) -> DataFrame:
    """(s, o) of all answers.

    order="subjects": phase two runs forward from useful subjects; "objects": the
    mirrored expression, useful objects first. With ``prune`` phase two only enters
    states that phase one has marked as leading to an end. ``marks``: (node, mask) of states
    that may not be entered, in either phase; they name positions of the expression, so the
    mirrored one does not take them.
    """
    if options.order == "objects" and not arrive and marks is None:
        flipped = evaluate(g, reversed_tables, tables, RpqOptions(**{**options.__dict__, "order": "subjects"}), stats)
        return flipped.select(F.col("o").alias("s"), F.col("s").alias("o"))
    masks = Masks(tables)
    if options.range_start:
        leads = phase_one(g, tables, options, stats, arrive, marks=marks)
        starts = leads.filter(masks.some(masks.both(F.col("mask"), masks.lit(tables.initial)))).select("node")
    else:
        leads, starts = None, g.nodes()
    barred = marks
    if options.prune and leads is not None:
        # What phase one did not mark counts as visited: the complement per node.
        every = masks.lit((1 << tables.bits) - 1)
        barred = g.nodes().join(leads.select("node", F.col("mask").alias("_ok")), "node", "left").select("node", F.when(F.col("_ok").isNull(), every).otherwise(masks.without(every, F.col("_ok"))).alias("mask"))
        if marks is not None:
            barred = state.merged(barred.unionByName(marks), masks, [])
    chunks = options.origin_chunks
    if not chunks:
        # As many parts as keep (origins of a part) x (nodes that lead to an end) within bounds.
        of, origins = (leads if leads is not None else g.nodes()), starts
        chunks = max(1, -(-of.count() * origins.count() // options.most_state))
    out = None
    for k in range(chunks):
        part = starts.filter(F.pmod(F.xxhash64("node"), F.lit(chunks)) == k) if chunks > 1 else starts
        seeds = part.select(F.col("node").alias("origin"), "node", masks.lit(tables.initial).alias("mask"))
        seen = backward.traverse(g, tables, seeds, ["origin"], False, options, stats, arrive=arrive, premarked=barred, report=tables.nfa.mask(tables.nfa.last))
        last = masks.lit(tables.nfa.mask(tables.nfa.last))
        found = seen.filter(masks.some(masks.both(F.col("mask"), last))).select(F.col("origin").alias("s"), F.col("node").alias("o"))
        out = found if out is None else out.unionByName(found)
    if tables.nfa.nullable:
        out = out.union(g.nodes().select(F.col("node").alias("s"), F.col("node").alias("o"))).distinct()
    return out


__all__ = ["evaluate", "phase_one", "state", "useful_sources"]
