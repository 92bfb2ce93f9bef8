"""Both ends open, by sets of ends: the answers of all starts at once, instead of a search for each.

The product of graph and automaton, as far as paths pass a given label, is cut into its strongly connected
parts, in levels: a part only reaches parts of lower levels. A task takes a range of ends, one bit each, and
gives every part the OR of the rows of the parts that it steps to, level by level; so an edge is looked at once
a range, not once a start. Starts with equal rows are named together with their ends.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..automaton.bitparallel import Tables
from . import kernel
from .kernel import Local, Search

#: Words of 64 ends in a range at most, and words that a task holds of all parts, or of the steps of a level.
WORDS, HELD = 16, 1 << 24
#: Starts, and ends, of a row, whose pairs Spark holds until all are made; and rows that travel together.
TILE, ROWS = 64, 256


def components(start: list[int], to: list[int]) -> list[int]:
    """The strongly connected part of each cell; a part's number is above those of the parts that it reaches."""
    n = len(start) - 1
    at, seen, low, part = list(start), [0] * n, [0] * n, [-1] * n
    path: list[int] = []
    visits = parts = 0
    for root in range(n):
        if seen[root]:
            continue
        calls = [root]
        visits += 1
        seen[root] = low[root] = visits
        path.append(root)
        while calls:
            x = calls[-1]
            i = at[x]
            if i < start[x + 1]:
                at[x] = i + 1
                y = to[i]
                if not seen[y]:
                    visits += 1
                    seen[y] = low[y] = visits
                    path.append(y)
                    calls.append(y)
                elif part[y] < 0 and seen[y] < low[x]:
                    low[x] = seen[y]
                continue
            calls.pop()
            if calls and low[x] < low[calls[-1]]:
                low[calls[-1]] = low[x]
            if low[x] == seen[x]:
                while part[x] < 0:
                    part[path.pop()] = parts
                parts += 1
    return part


@dataclass
class Levels:
    """Parts, numbered by level, and their steps, sorted by the part that they leave."""

    #: First part, and first step, of each level, and the end.
    parts: np.ndarray
    steps: np.ndarray
    to: np.ndarray
    #: First step of each part above the lowest level.
    first: np.ndarray
    #: Nodes that may start, and their parts; nodes that may end, and by (part, place in ``ends``) where they do.
    starts: np.ndarray
    start_parts: np.ndarray
    ends: np.ndarray
    at: np.ndarray
    place: np.ndarray

    def words(self) -> int:
        widest = int(np.diff(self.steps).max(initial=1))
        return max(1, min(WORDS, HELD // max(1, int(self.parts[-1]), widest)))

    def rows(self, lo: int, words: int) -> np.ndarray:
        """For each start, the bits of those of 64 * ``words`` ends from ``lo`` that it reaches."""
        reached = np.zeros((int(self.parts[-1]), words), np.uint64)
        own = (self.place >= lo) & (self.place < lo + 64 * words)
        bit = self.place[own] - lo
        np.bitwise_or.at(reached, (self.at[own], bit >> 6), np.uint64(1) << (bit & 63).astype(np.uint64))
        lowest = self.parts[1] if len(self.parts) > 1 else 0
        for k in range(1, len(self.parts) - 1):
            a, b, i, j = self.parts[k], self.parts[k + 1], self.steps[k], self.steps[k + 1]
            reached[a:b] |= np.bitwise_or.reduceat(reached[self.to[i:j]], self.first[a - lowest : b - lowest] - i, axis=0)
        return reached[self.start_parts]


def levels(ahead: Local, behind: Local, tables: Tables, through: int) -> Levels:
    """The parts of the product that lie on paths through the states ``through``; these are walked both ways
    from where a step enters these states. ``ahead``, ``behind``: the steps along the path and against it."""
    v, bits, last = len(ahead.names), tables.bits, tables.nfa.mask(tables.nfa.last)
    marks = np.zeros(v, np.int64)
    enters = np.unique(ahead.to[ahead.b & through != 0])
    for g, back in ((ahead, False), (behind, True)):
        seen = np.zeros(v, np.int64)
        if len(enters):
            seeds = np.zeros(v, np.int64)
            np.bitwise_or.at(seeds, ahead.to, ahead.b & through)
            Search(g, tables.arrays(back), tables.chunk_bits, back).run(np.zeros(len(enters), np.int64), enters, seeds[enters], 0, marks=seen)
        marks |= seen
    cells = np.sort(np.concatenate([np.flatnonzero(marks >> q & 1) * bits + q for q in range(bits)]))
    number = lambda node, q: np.searchsorted(cells, node * bits + q)
    leaves, source, to = np.repeat(np.arange(v), np.diff(ahead.start)), [], []
    for q in range(bits):
        new = np.where(marks[leaves] >> q & 1 != 0, ahead.b & np.int64(tables.succ[q]) & marks[ahead.to], 0)
        for r in range(bits):
            hit = new >> r & 1 != 0
            source.append(number(leaves[hit], q))
            to.append(number(ahead.to[hit], r))
    source, to = np.concatenate(source), np.concatenate(to)
    order = np.argsort(source, kind="stable")
    first = np.concatenate([[0], np.cumsum(np.bincount(source, minlength=len(cells)))])
    part = np.array(components(first.tolist(), to[order].tolist()), np.int64)
    n = int(part.max(initial=-1)) + 1
    # Steps between parts; these are numbered so that a step leads to a lower number.
    steps = np.unique(part[source] * n + part[to]) if n else np.empty(0, np.int64)
    source, to = steps // max(1, n), steps % max(1, n)
    source, to = source[source != to], to[source != to]
    level = [0] * n
    for a, b in zip(source.tolist(), to.tolist()):
        if level[b] >= level[a]:
            level[a] = level[b] + 1
    level = np.array(level, np.int64)
    order = np.argsort(level, kind="stable")
    renamed = np.empty(n, np.int64)
    renamed[order] = np.arange(n)
    bounds = np.concatenate([[0], np.cumsum(np.bincount(level))]) if n else np.zeros(1, np.int64)
    own = renamed[source]
    sort = np.argsort(own, kind="stable")
    own, to = own[sort], renamed[to[sort]]
    # Ends of one part, or of parts that were left one after the other, are neighbours, so that many starts have equal rows.
    node, state = cells // bits, cells % bits
    closing = np.flatnonzero(np.int64(last) >> state & 1 != 0)
    closing = closing[np.lexsort((node[closing], part[closing]))]
    _, where = np.unique(node[closing], return_index=True)
    ends = node[closing][np.sort(where)]
    place = np.empty(v, np.int64)
    place[ends] = np.arange(len(ends))
    opening = np.flatnonzero(np.int64(tables.initial) >> state & 1 != 0)
    return Levels(bounds, np.searchsorted(own, bounds), to, np.searchsorted(own, np.arange(bounds[1] if n else 0, n)), node[opening], renamed[part[opening]], ends, renamed[part[closing]], place[node[closing]])


def _listed(values: np.ndarray, begin: np.ndarray, size: np.ndarray, names: pa.Array) -> pa.ListArray:
    """Lists of the names of runs of ``values``."""
    offsets = np.concatenate([[0], np.cumsum(size)])
    at = np.repeat(begin - offsets[:-1], size) + np.arange(offsets[-1])
    return pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), names.take(pa.array(values[at])))


def tiles(found: Levels, names: pa.Array, lo: int, words: int):
    """Lists of starts and of ends, as Arrow batches: all pairs of a row are answers, and no pair is in two rows."""
    rows = np.ascontiguousarray(found.rows(lo, words))
    some = np.flatnonzero(rows.any(axis=1))
    if not len(some):
        return
    kinds, which, size = np.unique(rows[some].view(f"V{8 * words}").ravel(), return_inverse=True, return_counts=True)
    kinds = kinds.view(np.uint8).reshape(len(kinds), 8 * words)
    starts, before = found.starts[some[np.argsort(which, kind="stable")]], np.cumsum(size) - size
    for k in range(0, len(kinds), ROWS):
        kind, bit = np.nonzero(np.unpackbits(kinds[k : k + ROWS], axis=1, bitorder="little"))
        own, ends = size[k : k + ROWS], np.bincount(kind)
        first = np.cumsum(ends) - ends
        # Every run of starts of a kind meets every run of its ends.
        across = -(-ends // TILE)
        n = -(-own // TILE) * across
        of = np.repeat(np.arange(len(n)), n)
        i, j = np.divmod(np.arange(len(of)) - np.repeat(np.cumsum(n) - n, n), across[of])
        for lot in range(0, len(of), ROWS):
            x, a, b = of[lot : lot + ROWS], i[lot : lot + ROWS] * TILE, j[lot : lot + ROWS] * TILE
            s = _listed(starts, before[k + x] + a, np.minimum(TILE, own[x] - a), names)
            o = _listed(found.ends[lo + bit], first[x] + b, np.minimum(TILE, ends[x] - b), names)
            yield pa.RecordBatch.from_arrays([s, o], names=["s", "o"])


def pairs(spark: SparkSession, rows: pa.Table, tables: Tables, through: int) -> DataFrame:
    """(s, o) of all answers by paths that enter one of the states ``through``; no pair comes twice."""
    ahead, behind = (kernel.local(rows, tables, back) for back in (False, True))
    found = levels(ahead, behind, tables, through)
    if not len(found.ends):
        return spark.createDataFrame([], "s string, o string")
    names, words = ahead.names, found.words()
    sent = spark.sparkContext.broadcast((found, names))

    def work(batches):
        found, names = sent.value
        names = pa.array(names, pa.string())
        for b in batches:
            for lo in b.column(0).to_pylist():
                yield from tiles(found, names, lo, words)

    ranges = spark.range(0, len(found.ends), 64 * words, -(-len(found.ends) // (64 * words)))
    out = ranges.mapInArrow(work, "s array<string>, o array<string>")
    return out.select(F.explode("s").alias("s"), "o").select("s", F.explode("o").alias("o"))
