"""The frontier executor: one DataFrame job per breadth-first level.

A round joins the frontier with the pruned steps, applies the automaton as a
column expression, merges the states of a node map-side and after the shuffle, and keeps
the states that are new. Rounds are saved, and visited states are the union of the rounds,
so nothing is rewritten.
"""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..automaton.bitparallel import Masks, Tables
from ..graph.model import Graph
from . import state
from .options import RpqOptions, RunStats
from .store import Store


class Timeout(RuntimeError):
    pass


def steps(g: Graph, masks: Masks, backward: bool, options: RpqOptions, arrive: dict | None = None) -> DataFrame:
    """The pruned steps of a traversal; a state with a must-pass node is entered only there."""
    edges = state.moves(g, masks, backward, options.label_pruning)
    if arrive:
        enters = F.col("at") if backward else F.col("to")
        for bit, node in arrive.items():
            keep = F.when(enters == node, F.col("b")).otherwise(masks.without(F.col("b"), masks.lit(bit)))
            edges = edges.withColumn("b", keep)
        edges = edges.filter(masks.some(F.col("b")))
    return edges


def barred(rows: DataFrame, marks: DataFrame | None, masks: Masks) -> DataFrame:
    """(keys, node, mask) without the states that ``marks`` (node, mask) forbids."""
    if marks is None:
        return rows
    m = marks.select("node", F.col("mask").alias("_m"))
    left = F.when(F.col("_m").isNull(), F.col("mask")).otherwise(masks.without(F.col("mask"), F.col("_m")))
    return rows.join(m, "node", "left").withColumn("mask", left).filter(masks.some(F.col("mask"))).drop("_m")


class Visited:
    """Visited states: a compacted table and the rounds since, so that a round reads each state a bounded number of times."""

    EVERY = 8

    def __init__(self, store: Store, masks: Masks, keys: list[str]):
        self.store, self.masks, self.keys, self.base, self.recent, self.k = store, masks, keys, None, [], 0

    def add(self, rows: DataFrame) -> None:
        self.recent.append(rows)
        if len(self.recent) > self.EVERY:
            self.base = self.store.save(state.merged(self.all(), self.masks, self.keys), f"visited/{self.k}")
            self.recent, self.k = [], self.k + 1

    def all(self) -> DataFrame:
        parts = ([self.base] if self.base is not None else []) + self.recent
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out


def traverse(g: Graph, tables: Tables, seeds: DataFrame, keys: list[str], backward: bool, options: RpqOptions, stats: RunStats | None = None, stop=None, arrive: dict | None = None, premarked: DataFrame | None = None, report: int = 0, step=None) -> DataFrame:
    """All visited (keys, node, mask) from seeds.

    ``stop(new)`` ends the traversal early when it gives true for a saved round.
    ``step(frontier)`` gives the candidates of a round in place of a join with the edges.
    ``premarked``: (node, mask) of states that are never entered, nor started in.
    ``report``: states whose nodes are answers; a traversal ends once there are
    ``options.limit`` of them (a node counts once for each of these states that it gets). The edges of a stored graph are read from where they lie,
    in the folders of the labels; those of another graph are written out first. A
    frontier of up to ``options.broadcast_rows`` rows, which are counted, is sent to the
    edges, so that these are not shuffled.
    """
    masks, store, stats = Masks(tables), Store(g.spark, "rpq"), stats if stats is not None else RunStats()
    began, answers = time.time(), 0
    edges = steps(g, masks, backward, options, arrive)
    if not g.is_stored:
        edges = store.save(edges, "edges")
    visited = Visited(store, masks, keys)

    def saved(rows: DataFrame, k: int) -> tuple[DataFrame, int, int, int]:
        """A round written, and its rows, states, and answers, counted while it is written."""
        seen = Observation()
        hits = F.count_if(masks.some(masks.both(F.col("mask"), masks.lit(report)))) if report else F.lit(0)
        observed = rows.observe(seen, F.count(F.lit(1)).alias("n"), F.sum(masks.size(F.col("mask"))).alias("k"), hits.alias("hits") if report else F.max(F.lit(0)).alias("hits"))
        out = store.save(observed, f"rounds/{k}")
        got = seen.get
        return out, got["n"], got["k"] or 0, got["hits"] or 0

    start = barred(state.merged(seeds, masks, keys), premarked, masks).select(*keys, "node", "mask")
    frontier, n, k, hits = saved(start, 0)
    visited.add(frontier)
    while n:
        stats.rounds += 1
        stats.frontier_rows += n
        stats.states += k
        answers += hits
        if stop is not None and stop(frontier) or report and options.limit is not None and answers >= options.limit * report.bit_count():
            break
        if options.timeout_s is not None and time.time() - began > options.timeout_s:
            raise Timeout(f"{options.timeout_s} s are over")
        if stats.rounds > options.most_rounds:
            raise RuntimeError("more rounds than allowed")
        sent = F.broadcast(frontier) if n <= options.broadcast_rows else frontier
        candidates = step(frontier) if step is not None else state.step(sent, edges, masks, keys, backward, options.merge_states)
        if not options.merge_states:
            candidates = candidates.distinct()
        new = state.fresh(barred(candidates, premarked, masks).select(*keys, "node", "mask"), visited.all() if options.visited_pruning else frontier, masks, keys)
        if not options.merge_states:
            new = new.distinct()
        frontier, n, k, hits = saved(new, stats.rounds)
        visited.add(frontier)
    return state.merged(visited.all(), masks, keys)


def seeds_of(g: Graph, masks: Masks, nodes: DataFrame, mask: int) -> DataFrame:
    return nodes.select("node").distinct().withColumn("mask", masks.lit(mask))
