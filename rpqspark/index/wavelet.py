"""Wavelet trees over the columns of the index: a kernel for one shard, and the
same levels as a DataFrame. Positions are half-open and count from 0; symbols are 0..sigma-1."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..exec.store import Store
from ..graph.encode import numbered, running
from .bits import Bits


class Wavelet:
    """A perfect binary tree, level by level; a node is a (level, prefix) with its range."""

    def __init__(self, seq, sigma: int | None = None):
        seq = np.asarray(seq, np.int64)
        self.n, self.sigma = len(seq), int(sigma if sigma is not None else seq.max(initial=0) + 1)
        self.height = max(1, (self.sigma - 1).bit_length())
        self.levels: list[Bits] = []
        self.starts: list[np.ndarray] = []
        for level in range(self.height):
            prefix = seq >> (self.height - level)
            order = np.argsort(prefix, kind="stable")
            self.levels.append(Bits(seq[order] >> (self.height - level - 1) & 1))
            self.starts.append(np.concatenate([[0], np.cumsum(np.bincount(prefix, minlength=1 << level))]).astype(np.int64))
        #: First position of each symbol if the sequence were sorted.
        self.C = np.concatenate([[0], np.cumsum(np.bincount(seq, minlength=1 << self.height))]).astype(np.int64)

    def _down(self, level: int, prefix: int, b: int, e: int):
        """Ranges [b, e) of both children, relative to their nodes."""
        bits, at = self.levels[level], int(self.starts[level][prefix])
        base = int(bits.rank1(at))
        ones_b, ones_e = int(bits.rank1(at + b)) - base, int(bits.rank1(at + e)) - base
        return (b - ones_b, e - ones_e), (ones_b, ones_e)

    def access(self, i: int) -> int:
        prefix = 0
        for level in range(self.height):
            bit = self.levels[level][int(self.starts[level][prefix]) + i]
            (i0, _), (i1, _) = self._down(level, prefix, i, i)
            i, prefix = (i1 if bit else i0), prefix * 2 + bit
        return prefix

    def rank(self, c: int, i: int) -> int:
        """Occurrences of c among the first i symbols."""
        prefix = 0
        for level in range(self.height):
            bit = c >> (self.height - level - 1) & 1
            (i0, _), (i1, _) = self._down(level, prefix, i, i)
            i, prefix = (i1 if bit else i0), prefix * 2 + bit
        return i

    def _visit(self, b: int, e: int, enter):
        """(symbol, b, e) of the leaves met by [b, e) whose every node ``enter`` lets through."""
        out, stack = [], [(0, 0, b, e)]
        while stack:
            level, prefix, b, e = stack.pop()
            if b >= e or not enter(level, prefix):
                continue
            if level == self.height:
                out.append((prefix, b, e))
                continue
            zero, one = self._down(level, prefix, b, e)
            stack += [(level + 1, prefix * 2 + 1, *one), (level + 1, prefix * 2, *zero)]
        return out

    def distinct(self, b: int, e: int):
        """(symbol, rank before, rank after) of the distinct symbols of [b, e), in order."""
        return self._visit(b, e, lambda level, prefix: True)

    def distinct_masked(self, b: int, e: int, d: int, masks: list[list[int]]):
        """Distinct symbols whose label mask meets d; subtrees that do not are skipped."""
        return self._visit(b, e, lambda level, prefix: masks[level][prefix] & d)

    def distinct_unvisited(self, b: int, e: int, d: int, seen: list[list[int]]):
        """Distinct symbols that lack some state of d, with the states that are new;
        marks them. An inner node holds the states that all symbols below it have."""
        found = self._visit(b, e, lambda level, prefix: d & ~seen[level][prefix])
        out = []
        for c, *_ in found:
            out.append((c, d & ~seen[self.height][c]))
            mark(seen, c, d, self.height)
        return out

    def intersect(self, r1: tuple[int, int], r2: tuple[int, int]) -> list[int]:
        """Symbols that occur in both ranges."""
        out, stack = [], [(0, 0, r1, r2)]
        while stack:
            level, prefix, a, b = stack.pop()
            if a[0] >= a[1] or b[0] >= b[1]:
                continue
            if level == self.height:
                out.append(prefix)
                continue
            (a0, a1), (b0, b1) = self._down(level, prefix, *a), self._down(level, prefix, *b)
            stack += [(level + 1, prefix * 2 + 1, a1, b1), (level + 1, prefix * 2, a0, b0)]
        return out

    def next_value(self, b: int, e: int, x: int) -> int | None:
        """The smallest symbol >= x in [b, e)."""
        got = self._visit(b, e, lambda level, prefix: (prefix + 1 << (self.height - level)) > x)
        return got[0][0] if got else None

    def nbytes(self) -> int:
        return sum(x.nbytes() for x in self.levels)


def build(seq, sigma: int | None = None) -> Wavelet:
    return Wavelet(seq, sigma)


def label_masks(height: int, masks: dict[int, int]) -> list[list[int]]:
    """Per level, the OR of the leaf masks below each node."""
    rows = [[masks.get(c, 0) for c in range(1 << height)]]
    for _ in range(height):
        below = rows[0]
        rows.insert(0, [below[2 * i] | below[2 * i + 1] for i in range(len(below) // 2)])
    return rows


def no_states(height: int, present: set[int]) -> list[list[int]]:
    """Empty visited masks; leaves that never occur count as having every state."""
    full = -1
    rows = [[0 if c in present else full for c in range(1 << height)]]
    for _ in range(height):
        below = rows[0]
        rows.insert(0, [below[2 * i] & below[2 * i + 1] for i in range(len(below) // 2)])
    return rows


def mark(seen: list[list[int]], c: int, d: int, height: int) -> None:
    """Adds states to a leaf; each node above becomes the AND of its two children, never an OR."""
    seen[height][c] |= d
    for level in range(height - 1, -1, -1):
        c >>= 1
        seen[level][c] = seen[level + 1][2 * c] & seen[level + 1][2 * c + 1]


def level_table(column: DataFrame, height: int, store: Store) -> DataFrame:
    """(level, block, word, ones_before) of the bit vectors of a column (pos from 1, symbol from 0).

    All levels are numbered by one range sort of (level, prefix, pos); words and the ones before
    them are sums, with offsets per partition.
    """
    levels = column.select("pos", "symbol", F.explode(F.sequence(F.lit(0), F.lit(height - 1))).alias("level"))
    bits = levels.select("level", "pos", F.expr(f"shiftright(symbol, {height} - level)").alias("prefix"), F.expr(f"shiftright(symbol, {height} - level - 1) & 1").cast("int").alias("bit"))
    placed = numbered(bits, ["level", "prefix", "pos"], "n", store, "level_rows", start=0)
    n = column.agg(F.count("*").alias("n")).first().n
    at = F.col("n") - F.col("level") * F.lit(n)
    words = placed.withColumn("at", at).groupBy("level", F.floor(F.col("at") / 64).cast("int").alias("block")).agg(F.bit_or(F.expr("shiftleft(cast(bit AS bigint), cast(at % 64 AS int))")).alias("word"), F.sum("bit").alias("ones"))
    before = running(words, ["level", "block"], "ones", "before", store, "level_words")
    first = F.broadcast(before.filter("block = 0").select("level", F.col("before").alias("base")))
    return before.join(first, "level").select("level", "block", "word", (F.col("before") - F.col("base")).alias("ones_before"))


def ranks(levels: DataFrame, asked: DataFrame) -> DataFrame:
    """(level, i, ones): rank_1 of the asked (level, i) by a count inside one word."""
    a = asked.withColumn("block", F.floor(F.col("i") / 64).cast("int"))
    low = F.when(F.col("i") % 64 == 0, F.lit(0).cast("long")).otherwise(F.col("word").bitwiseAND(F.expr("shiftrightunsigned(-1L, 64 - cast(i % 64 as int))")))
    return a.join(levels, ["level", "block"]).select("level", "i", (F.col("ones_before") + F.bit_count(low)).cast("long").alias("ones"))
