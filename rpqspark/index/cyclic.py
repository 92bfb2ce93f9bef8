"""Cyclic triple index: the last columns of three sorted orders of the triples, with the
steps between them.

L_o belongs to the order (s, p, o), L_s to (p, o, s), L_p to (o, s, p). Position i of one
column leads to position C[c] + rank(c, i) of the next; three steps give a triple back.
Positions count from 1, symbols are the numbers of the dictionaries. Orders are built by
range sorts with offsets per partition, never by one global window.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..exec.store import Store
from ..graph.encode import numbered, running

#: Column -> its order, and the column that a step from it leads to.
ORDERS = {"o": ["s", "p", "o"], "s": ["p", "o", "s"], "p": ["o", "s", "p"]}
NEXT = {"p": "s", "s": "o", "o": "p"}


@dataclass
class CyclicIndex:
    """``columns[c]``: (pos, symbol, rank), the rank of the symbol up to this position;
    ``starts[c]``: (symbol, start, upto), the numbers of smaller symbols of that kind, and of
    those and equal ones."""

    columns: dict[str, DataFrame]
    starts: dict[str, DataFrame]
    n: int

    #: Positions of a symbol that are looked through together.
    BUCKET = 1 << 16

    def lf(self, positions: DataFrame, col: str) -> DataFrame:
        """(pos, symbol, next): from positions of a column to positions of the column before it
        in the cycle, where triples are sorted by this symbol first."""
        met = positions.select("pos").join(self.columns[col], "pos").join(self.starts[col], "symbol")
        return met.select("pos", "symbol", (F.col("start") + F.col("rank")).alias("next"))

    def triple_at(self, positions: DataFrame, col: str = "p") -> DataFrame:
        """(pos, s, p, o) of positions in a column, by three steps round the cycle."""
        rows = positions.select(F.col("pos").alias("at"), "pos")
        for _ in range(3):
            step = self.lf(rows, col).distinct()
            rows = rows.join(step, "pos").drop("pos").withColumnRenamed("symbol", col).withColumnRenamed("next", "pos")
            col = NEXT[col]
        return rows.select(F.col("at").alias("pos"), "s", "p", "o")

    def rank(self, asked: DataFrame, col: str) -> DataFrame:
        """(symbol, pos, rank): how often a symbol stands in a column up to a position.

        An as-of lookup: positions that are asked and positions where the symbol stands are
        sorted together by (symbol, bucket of positions); the last rank before a position holds
        in its bucket, and the last of earlier buckets where its own has none.
        """
        bucket = F.floor(F.col("pos") / self.BUCKET)
        asked = asked.select("symbol", "pos").distinct()
        there = self.columns[col].join(asked.select("symbol").distinct(), "symbol", "left_semi").select("symbol", "pos", F.col("rank").alias("r"))
        both = there.withColumn("ask", F.lit(False)).unionByName(asked.withColumn("r", F.lit(None).cast("long")).withColumn("ask", F.lit(True))).withColumn("bucket", bucket)
        # Of equal positions the symbol's own comes first; a rank only grows, so the largest before is the last.
        inside = Window.partitionBy("symbol", "bucket").orderBy("pos", "ask").rowsBetween(Window.unboundedPreceding, 0)
        found = both.withColumn("own", F.max("r").over(inside)).filter("ask").select("symbol", "pos", "bucket", "own")
        last = both.groupBy("symbol", "bucket").agg(F.max("r").alias("top"))
        earlier = last.withColumn("before", F.max("top").over(Window.partitionBy("symbol").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1))).select("symbol", "bucket", "before")
        return found.join(earlier, ["symbol", "bucket"]).select("symbol", "pos", F.coalesce("own", "before", F.lit(0)).cast("long").alias("rank"))

    def backward(self, ranges: DataFrame, col: str) -> DataFrame:
        """(b, e, symbol) with inclusive ranges of a column to the ranges (nb, ne) of the triples
        that have this symbol before them; empty ones are dropped.

        Two ranks a range, at its end and before its start, whatever its length.
        """
        asked = ranges.select("symbol", (F.col("b") - 1).alias("pos")).unionByName(ranges.select("symbol", F.col("e").alias("pos")))
        got = self.rank(asked, col)
        low = got.select("symbol", (F.col("pos") + 1).alias("b"), F.col("rank").alias("lo"))
        high = got.select("symbol", F.col("pos").alias("e"), F.col("rank").alias("hi"))
        met = ranges.select("b", "e", "symbol").join(low, ["symbol", "b"]).join(high, ["symbol", "e"]).filter("hi > lo")
        return met.join(self.starts[col], "symbol").select("b", "e", "symbol", (F.col("start") + F.col("lo") + 1).alias("nb"), (F.col("start") + F.col("hi")).alias("ne"))

    def symbols_of(self, ranges: DataFrame, col: str) -> DataFrame:
        """(b, e, symbol): the distinct symbols of disjoint ranges of a column. Ranges become their
        positions, bucket by bucket, which meet the column by an equi-join."""
        size = F.lit(self.BUCKET).cast("long")
        parts = ranges.select("b", "e").distinct().select("b", "e", F.explode(F.sequence(F.floor(F.col("b") / size), F.floor(F.col("e") / size))).alias("k"))
        places = parts.select("b", "e", F.explode(F.sequence(F.greatest("b", F.col("k") * size), F.least(F.col("e"), (F.col("k") + 1) * size - 1))).alias("pos"))
        return places.join(self.columns[col].select("pos", "symbol"), "pos").select("b", "e", "symbol").distinct()

    def interval(self, lo: int, hi: int, col: str) -> DataFrame:
        """(b, e): the range of all triples whose first part, in the order that ``col`` counts, lies in [lo, hi]."""
        own = self.starts[col].filter((F.col("symbol") >= lo) & (F.col("symbol") <= hi))
        return own.agg((F.min("start") + 1).alias("b"), F.max("upto").alias("e")).filter("b <= e")

    def range_of(self, s: int, p: int | None = None) -> DataFrame:
        """(b, e): positions in L_o of the triples with subject s, or with s and p.

        With a label: the label's range in L_s by the counts, then one backward step by s.
        """
        nodes = self.columns["o"].sparkSession.createDataFrame([(s if p is None else p,)], "node long")
        block = self.object_range(nodes, "s" if p is None else "p").select("b", "e")
        if p is None:
            return block
        return self.backward(block.withColumn("symbol", F.lit(s).cast("long")), "s").select(F.col("nb").alias("b"), F.col("ne").alias("e"))

    def object_range(self, nodes: DataFrame, col: str = "o") -> DataFrame:
        """(node, b, e): the range of L_p of the triples with this object, from the counts alone."""
        s = self.starts[col]
        return nodes.join(s, nodes["node"] == s["symbol"]).select("node", (F.col("start") + 1).alias("b"), F.col("upto").alias("e")).filter("b <= e")


def starts(column: DataFrame, store: Store, name: str) -> DataFrame:
    """(symbol, start, upto): how many symbols are smaller, and how many not larger."""
    counts = column.groupBy("symbol").agg(F.count("*").alias("k"))
    return running(counts, ["symbol"], "k", "start", store, f"starts_{name}").select("symbol", "start", (F.col("start") + F.col("k")).alias("upto"))


def build(edges: DataFrame, orders: tuple[str, ...] = ("p", "s", "o")) -> CyclicIndex:
    """``edges``: distinct (s, p, o) as numbers, inverses included if they are wanted."""
    spark = edges.sparkSession
    store = Store(spark, "cyclic")
    edges = store.save(edges.select(*[F.col(c).cast("long").alias(c) for c in "spo"]), "edges")
    columns, counts = {}, {}
    for c in orders:
        placed = store.save(numbered(edges, ORDERS[c], "pos", store, f"parts_{c}"), f"order_{c}").select("pos", F.col(c).alias("symbol"))
        # A symbol's rank is its turn among equal symbols; hot symbols are numbered by
        # range partitions of (symbol, pos), so no task holds one symbol alone.
        ranked = numbered(placed, ["symbol", "pos"], "turn", store, f"turns_{c}")
        counts[c] = starts(placed, store, c)
        columns[c] = store.save(ranked.join(counts[c], "symbol").select("pos", "symbol", (F.col("turn") - F.col("start")).alias("rank")), f"column_{c}")
    return CyclicIndex(columns, counts, edges.count())
