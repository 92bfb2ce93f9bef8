"""Bit-parallel simulation: sets of states are masks.

Forward, D becomes T[D] & B[c]; backward, D becomes T'[D & B[c]]. T and T' are
cut into tables over ``chunk_bits`` bits that are OR-ed; both distribute over
unions, so a DataFrame step is an OR over states inside whole-stage code. Masks of
more than 63 states are arrays of longs, handled word by word.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..lang.ast import Expr
from . import position

WORD = 63


@dataclass
class Tables:
    nfa: position.PositionNFA
    chunk_bits: int = 8
    #: States in a word; more states make wide masks.
    word_bits: int = WORD

    def __post_init__(self):
        m = self.nfa.m
        self.bits = m + 1
        self.succ = [self.nfa.mask(self.nfa.after(m - b)) for b in range(self.bits)]
        self.pred = [0] * self.bits
        for b, to in enumerate(self.succ):
            for t in range(self.bits):
                if to >> t & 1:
                    self.pred[t] |= 1 << b
        self.T, self.R = self._chunks(self.succ), self._chunks(self.pred)
        self.B: dict[tuple[str, bool], int] = {}
        for q, c in enumerate(self.nfa.positions, 1):
            if not c.negated:
                for s in c.labels:
                    self.B[s] = self.B.get(s, 0) | self.nfa.bit(q)
        self._negated = [(c, self.nfa.bit(q)) for q, c in enumerate(self.nfa.positions, 1) if c.negated]

    def _chunks(self, rows: list[int]) -> list[list[int]]:
        out = []
        for lo in range(0, self.bits, self.chunk_bits):
            part = rows[lo : lo + self.chunk_bits]
            table = [0] * (1 << len(part))
            for x in range(1, len(table)):
                low = x & -x
                table[x] = table[x ^ low] | part[low.bit_length() - 1]
            out.append(table)
        return out

    def _look(self, chunks: list[list[int]], d: int) -> int:
        out = 0
        for k, table in enumerate(chunks):
            out |= table[d >> k * self.chunk_bits & len(table) - 1]
        return out

    @property
    def initial(self) -> int:
        return self.nfa.initial

    @property
    def final(self) -> int:
        return self.nfa.final

    @property
    def wide(self) -> bool:
        return self.bits > self.word_bits

    def label(self, name: str, inverse: bool = False) -> int:
        """States that a label enters; labels outside the expression are never stored."""
        out = self.B.get((name, inverse), 0)
        for c, bit in self._negated:
            if c.holds(name, inverse):
                out |= bit
        return out

    def forward(self, d: int, name: str, inverse: bool = False) -> int:
        return self._look(self.T, d) & self.label(name, inverse)

    def backward(self, d: int, name: str, inverse: bool = False) -> int:
        return self._look(self.R, d & self.label(name, inverse))

    def used(self, names) -> dict[tuple[str, bool], int]:
        """Masks of the labels of a graph that the expression can read."""
        known = {(n, i): self.label(n, i) for n in names for i in (False, True)} if self._negated else {s: self.label(*s) for s in self.B}
        return {s: m for s, m in known.items() if m}

    def arrays(self, backward: bool) -> list[np.ndarray]:
        return [np.array(t, np.int64) for t in (self.R if backward else self.T)]


def compile(e: Expr, chunk_bits: int = 8, word_bits: int = WORD) -> Tables:
    return Tables(position.build(e), chunk_bits, word_bits)


class Masks:
    """Column operations on masks of a table: longs, or arrays of longs."""

    def __init__(self, tables: Tables):
        self.tables = tables
        self.words = -(-tables.bits // tables.word_bits) if tables.wide else 0
        self.type = "array<bigint>" if self.words else "bigint"

    def parts(self, x: int) -> list[int]:
        w = self.tables.word_bits
        return [x >> k * w & (1 << w) - 1 for k in range(self.words)]

    def value(self, x: int):
        return self.parts(x) if self.words else x

    def lit(self, x: int) -> Column:
        return F.array(*[F.lit(v).cast("long") for v in self.parts(x)]) if self.words else F.lit(x).cast("long")

    def both(self, a: Column, b: Column) -> Column:
        return F.zip_with(a, b, lambda x, y: x.bitwiseAND(y)) if self.words else a.bitwiseAND(b)

    def without(self, a: Column, b: Column) -> Column:
        return F.zip_with(a, b, lambda x, y: x.bitwiseAND(F.bitwise_not(y))) if self.words else a.bitwiseAND(F.bitwise_not(b))

    def some(self, a: Column) -> Column:
        return F.exists(a, lambda x: x != 0) if self.words else a != 0

    def either(self, name: str) -> Column:
        """Aggregate: union of the masks of a group."""
        if not self.words:
            return F.bit_or(name)
        return F.array(*[F.bit_or(F.col(name)[k]) for k in range(self.words)])

    def size(self, a: Column) -> Column:
        return F.aggregate(a, F.lit(0).cast("long"), lambda s, x: s + F.bit_count(x)) if self.words else F.bit_count(a).cast("long")

    def _or(self, x: Column, rows: list[int], word: int | None) -> Column:
        """OR of rows[q] over the set bits of x; bits with equal rows share a test."""
        groups: dict[int, int] = {}
        w, cut = self.tables.word_bits, (lambda v: v) if word is None else (lambda v: v >> word * self.tables.word_bits & (1 << self.tables.word_bits) - 1)
        for q, to in enumerate(rows):
            if cut(to):
                groups[cut(to)] = groups.get(cut(to), 0) | 1 << q
        terms = []
        for to, bits in groups.items():
            if word is None:
                hit = x.bitwiseAND(F.lit(bits).cast("long")) != 0
            else:
                hit = None
                for k in range(self.words):
                    part = bits >> k * w & (1 << w) - 1
                    if part:
                        test = x[k].bitwiseAND(F.lit(part).cast("long")) != 0
                        hit = test if hit is None else hit | test
            terms.append(F.when(hit, F.lit(to).cast("long")).otherwise(F.lit(0).cast("long")))
        out = terms[0] if terms else F.lit(0).cast("long")
        for t in terms[1:]:
            out = out.bitwiseOR(t)
        return out

    def step(self, x: Column, backward: bool) -> Column:
        """T'[x] or T[x] as an expression."""
        rows = self.tables.pred if backward else self.tables.succ
        return F.array(*[self._or(x, rows, k) for k in range(self.words)]) if self.words else self._or(x, rows, None)

    def label_frame(self, spark: SparkSession, names) -> DataFrame:
        """(p, inverse, b): masks of the labels that the expression reads."""
        rows = [(n, i, self.value(m)) for (n, i), m in sorted(self.tables.used(names).items())]
        return spark.createDataFrame(rows, f"p string, inverse boolean, b {self.type}")


def match_words(df: DataFrame, key: list[str], order: list[str], symbol: str, e: Expr) -> DataFrame:
    """(key, n, accepted): whether the symbols of a key, in order, spell a word of e.

    The simulation is a fold over the ordered symbols inside the JVM.
    """
    t = compile(e)
    masks = Masks(t)
    if masks.words:
        raise ValueError("the fold takes expressions of up to 62 symbols")
    names = {n for c in t.nfa.positions for n, _ in c.labels}
    read = F.lit(0).cast("long")
    for n in sorted(names):
        read = F.when(F.col("_s") == n, F.lit(t.label(n)).cast("long")).otherwise(read)
    if t._negated:
        other = sum(bit for c, bit in t._negated if (False in {i for _, i in c.labels}))
        read = F.when(~F.col("_s").isin(*names), F.lit(other).cast("long")).otherwise(read)
    rows = df.select(*key, F.struct(*order).alias("_o"), F.col(symbol).alias("_s")).withColumn("_b", read)
    words = rows.groupBy(*key).agg(F.transform(F.array_sort(F.collect_list(F.struct("_o", "_b"))), lambda x: x["_b"]).alias("_w"))
    end = F.aggregate("_w", masks.lit(t.initial), lambda d, b: masks.step(d, False).bitwiseAND(b))
    return words.select(*key, F.size("_w").cast("long").alias("n"), (end.bitwiseAND(masks.lit(t.final)) != 0).alias("accepted"))
