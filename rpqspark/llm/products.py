"""Exact top-k search by inner product, by norm-bucketed retrieval.

Vectors become whole numbers once, of two bytes each where they fit, and are dealt by length, longest
first, so a block holds vectors of similar length. The longest ones are met first and give each
query a threshold, its k-th best product; blocks whose longest vector cannot reach the least
threshold of a block of queries are left out of the join with it. A task keeps the k best of each
query over all blocks that it meets, so that it gives k rows a query and not k rows a block.

In a block the vectors lie in buckets, those with the same largest coordinate together. A bucket is
left out for a query if its longest vector cannot reach the threshold, or, where the threshold
taken relative to the lengths is a high bound on the cosine, if the range that it allows some coordinate
misses the bucket's. What is left is verified by its exact product: in single precision where lengths
show that no sum exceeds its whole numbers, else in double precision, else by whole numbers of any size.

Products that no long holds have a null score; they are ranked as doubles. An empty table, or one
without queries, gives an empty one.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import common, vectors

BUCKET, COSINE_FOR_COORDINATES = 256, 0.75
#: Whole numbers up to these are exact in single and in double precision.
_SINGLE, _EXACT = 2.0**24, 2.0**53
#: Found rows of a block of queries that wait until they are ranked.
WAITING = 1024
_NO_ID = np.iinfo(np.int64).max
_WHOLE = pa.schema([("vec_id", pa.int64()), ("v", pa.binary()), ("length", pa.float64()), ("cell", pa.int32())])


def whole_numbers(table: DataFrame, vector: str) -> DataFrame:
    """(vec_id, v, length, cell): rows that take part as whole numbers (``vectors.blocks`` says how), their length, and
    the coordinate that is largest with its sign."""
    kind = "array<float>" if dict(table.dtypes)[vector] == "array<float>" else "array<double>"
    rows = table.select(F.col("vec_id").cast("long").alias("vec_id"), F.col(f"`{vector}`").cast(kind).alias("v"))
    rows = rows.filter(F.col("vec_id").isNotNull() & F.col("v").isNotNull() & (F.size("v") > 0))

    def work(batches):
        for b in batches:
            ids, lists = b.column(0).to_numpy(), b.column(1)
            sizes = lists.value_lengths().to_numpy()
            flat, ends = lists.flatten().to_numpy(zero_copy_only=False), np.cumsum(sizes)  # a null is no number here
            for dim in np.unique(sizes).tolist():
                at = np.flatnonzero(sizes == dim)
                v = flat[((ends[at] - dim)[:, None] + np.arange(dim)).ravel()].reshape(-1, dim).astype(np.float64)
                fits = np.isfinite(v).all(axis=1)
                at, v = at[fits], np.floor(v[fits] * 256)
                largest = np.abs(v).argmax(axis=1)
                cells = (largest * 2 + (v[np.arange(len(v)), largest] < 0)).astype(np.int32)
                lengths, small = np.sqrt((v * v).sum(axis=1)), (np.abs(v) < 2**15).all(axis=1)
                for part, form in ((small, np.int16), (~small, np.float64)):
                    if part.any():
                        yield common.batch(_WHOLE, ids[at[part]], vectors.headed(v[part].astype(form)), lengths[part], cells[part])

    return rows.mapInArrow(work, "vec_id long, v binary, length double, cell int")


class Buckets:
    """The vectors of one block as whole numbers, in buckets."""

    def __init__(self, ids: np.ndarray, base: np.ndarray, bucket: int = BUCKET):
        self.ids, self.base = ids, base.astype(np.float64)
        self.length = np.sqrt((self.base**2).sum(axis=1))
        self.most, self.starts = float(self.length.max()), np.arange(0, len(ids), bucket)
        self.ends = np.append(self.starts[1:], len(ids))
        self.longest = np.maximum.reduceat(self.length, self.starts)
        unit = self.base / np.maximum(self.length, 1e-300)[:, None]
        self.low, self.high = np.minimum.reduceat(unit, self.starts), np.maximum.reduceat(unit, self.starts)
        self.single = self.base.astype(np.float32) if self.most < _SINGLE else None


class Best:
    """The k best so far of each query of a block."""

    def __init__(self, ids: np.ndarray, queries: np.ndarray, k: int, least: np.ndarray | None = None):
        """``least``: lengths that a vector must have to be among the best of a query, 0 if nothing is known."""
        self.ids, self.queries, self.k = ids, queries, k
        self.length = np.sqrt((queries.astype(np.float64) ** 2).sum(axis=1))
        self.most = float(self.length.max(initial=0))
        self.scores, self.found = np.full((len(ids), k), -np.inf), np.full((len(ids), k), _NO_ID)
        self.threshold = np.full(len(ids), -np.inf)
        if least is not None:
            # The margin only keeps more: lengths are rounded, products are not.
            known = (least > 0) & np.isfinite(least) & np.isfinite(self.length)
            self.threshold[known] = least[known] * self.length[known] * (1 - 1e-9) - 1e-6
        self.waiting: list = []
        self.count = 0

    def add(self, rows, scores, ids) -> None:
        keep = (ids != self.ids[rows]) & ((scores > self.scores[rows, -1]) | (ids < self.found[rows, -1]))
        self.waiting.append((rows[keep], scores[keep].astype(np.float64), ids[keep]))
        self.count += int(keep.sum())
        if self.count >= WAITING:
            self.rank()

    def rank(self) -> None:
        rows, scores, ids = (np.concatenate(x) for x in zip(*self.waiting)) if self.waiting else (np.empty(0, np.int64),) * 3
        self.waiting, self.count = [], 0
        at = np.unique(rows)
        rows = np.concatenate([np.repeat(at, self.k), rows])
        scores, ids = np.concatenate([self.scores[at].ravel(), scores]), np.concatenate([self.found[at].ravel(), ids])
        order = np.lexsort((ids, -scores, rows))
        rows, scores, ids = rows[order], scores[order], ids[order]
        place = np.arange(len(rows)) - np.searchsorted(rows, rows)
        top = place < self.k
        self.scores[rows[top], place[top]], self.found[rows[top], place[top]] = scores[top], ids[top]
        self.threshold[at] = np.maximum(self.threshold[at], self.scores[at, -1])

    def given(self):
        """(query id, vec_id, score, score as double) of the best."""
        self.rank()
        rows, places = np.nonzero(self.scores > -np.inf)
        scores = self.scores[rows, places]
        return self.ids[rows], self.found[rows, places], scores.astype(np.int64), scores


class Search:
    """What ``vectors.met`` asks for: the k largest integer products of each query over all blocks, exactly."""

    def __init__(self, k: int = 5, turns: int = vectors.COPIES):
        self.k, self.turns, self.room = k, turns, {}

    def start(self, q_ids, queries, least=None) -> Best:
        return Best(q_ids, queries, self.k, least)

    def meet(self, block: Buckets, best: Best):
        """Adds the products with a block; gives those that no double holds, k for each query, if there are any."""
        bound = best.most * block.most * (1 + 1e-9)  # no part of a product's sum exceeds it
        if not bound < _EXACT:
            return _large(block.ids, block.base, best.ids, best.queries, self.k)
        live = best.threshold[:, None] <= best.length[:, None] * block.longest * (1 + 1e-12) + 1e-9
        cosine = best.threshold / np.maximum(best.length * block.most, 1e-300)
        narrow = np.flatnonzero((cosine >= COSINE_FOR_COORDINATES) & live.any(axis=1))
        if len(narrow):
            # cos(a, b) is at most the cosine of the difference of both angles to an axis.
            unit = best.queries[narrow] / best.length[narrow, None]
            angle, most = np.arccos(np.clip(unit, -1, 1)), np.arccos(np.minimum(cosine[narrow], 1))[:, None] + 1e-7
            low, high = np.cos(np.minimum(angle + most, np.pi)) - 1e-7, np.cos(np.maximum(angle - most, 0)) + 1e-7
            live[narrow] &= ((low[:, None] <= block.high) & (high[:, None] >= block.low)).all(axis=2)
        base = block.single if bound < _SINGLE else block.base
        if live.mean() > 0.5:
            self._products(base, block.ids, best, slice(None) if live.any(axis=1).all() else np.flatnonzero(live.any(axis=1)))
        else:
            for b in np.flatnonzero(live.any(axis=0)).tolist():
                at = slice(block.starts[b], block.ends[b])
                self._products(base[at], block.ids[at], best, np.flatnonzero(live[:, b]))
        return None

    def _products(self, base, ids, best: Best, rows) -> None:
        queries, threshold = best.queries[rows].astype(base.dtype), best.threshold[rows]
        size = len(queries) * len(base)
        if len(self.room.get(base.dtype, ())) < size:  # kept, as memory of this size is dear to get anew for each pair
            self.room[base.dtype] = np.empty(size, base.dtype)
        scores = np.matmul(queries, base.T, out=self.room[base.dtype][:size].reshape(len(queries), len(base)))
        reach = np.flatnonzero(scores.max(axis=1) >= threshold)
        if not len(reach):
            return
        scores, threshold = scores[reach], threshold[reach]
        if (n := scores.shape[1]) > self.k + 1 and np.isneginf(threshold).any():
            # One more than k, as the query itself may be among them.
            threshold = np.maximum(threshold, np.partition(scores, n - self.k - 1, axis=1)[:, n - self.k - 1])
        r, c = np.nonzero(scores >= threshold[:, None])
        numbers = reach if isinstance(rows, slice) else rows[reach]
        best.add(numbers[r], scores[r, c], ids[c])


def buckets(ids, base, q_ids, queries, k: int = 5):
    """(query id, vec_id, score) of the k largest integer products among some vectors, of each query, exactly."""
    search, best = Search(k), Best(q_ids, np.floor(queries * 256), k)
    more = search.meet(Buckets(ids, np.floor(base * 256)), best)
    return (more or best.given())[:3]


def _large(ids, base, q_ids, queries, k):
    """Components too large for doubles: whole numbers of any size."""
    whole = [[int(x) for x in v] for v in base]
    out: list = [[], [], [], []]
    for q, v in zip(q_ids.tolist(), queries):
        v = [int(x) for x in v]
        for s, i in sorted((-sum(a * b for a, b in zip(v, w)), i) for i, w in zip(ids.tolist(), whole) if i != q)[:k]:
            for column, x in zip(out, (q, i, -s if -(2**63) < s <= 2**63 else None, float(-s))):
                column.append(x)
    return out


#: One in so many vectors, the longest, is met first; blocks of them that a task meets, unless ``COPIES`` tasks have more.
FIRST_ONE_IN, FIRST_BLOCKS = 16, 32
#: Lengths in one class differ by less than a twentieth.
CLASSES = 16


def largest(table: DataFrame, vector: str = "embedding", every: int = 50, k: int = 5) -> DataFrame:
    """The k largest integer inner products of every row whose vec_id ``every`` divides.

    Components are floor(256 * x), x as double. Vectors that take no part: see ``vectors``.
    """
    spark = table.sparkSession
    stage, turns = common.Stage(spark, "products"), common.partitions(spark)
    common.small_batches(spark, 4096)
    rows = stage.save(whole_numbers(table, vector), "whole")
    few, length = max(1, min(turns, 8)), F.col("length")
    own = stage.save(rows.filter(F.pmod("vec_id", F.lit(every)) == 0), "own")
    # Equal vectors have equal products: those of the k + 1 smallest ids are enough, one of which may be the query's.
    copy = F.dense_rank().over(Window.partitionBy("v").orderBy("vec_id"))
    rows = stage.save(rows.withColumn("copy", copy).filter(F.col("copy") <= k + 1).drop("copy"), "candidates")
    stage.drop("whole")
    stage.release()
    asked = stage.save(vectors.blocks(own.select("vec_id", "v").repartition(few), vectors.BLOCK_QUERIES), "queries")
    cut, n = rows.agg(F.percentile_approx(length, 1 - 1 / FIRST_ONE_IN, 1000), F.count("*")).first()
    if cut is None:
        return vectors.ranked(vectors.met(rows.select("vec_id", "v"), asked, False, Buckets, Search(k)), k, False)
    first = Search(k, -(-n // (FIRST_ONE_IN * FIRST_BLOCKS * vectors.BLOCK_VECTORS)) + few)
    long = rows.filter(length >= cut).select("vec_id", "v")
    best = stage.save(vectors.ranked(vectors.met(long, asked, False, Buckets, first), k, False, "approx"), "first")
    bounds = best.filter(F.col("rank") == k).select("query_id", "approx")
    # A vector reaches a threshold only if it is as long as the threshold is, relative to the query's length.
    need = F.try_divide("approx", length)
    own = own.join(bounds, F.col("vec_id") == F.col("query_id"), "left")
    own = own.select("vec_id", "v", F.when(need.isNull() | F.isnan(need) | (need < 0), F.lit(0.0)).otherwise(need).alias("need"))
    asked = stage.save(vectors.blocks(own.repartitionByRange(few, "need").sortWithinPartitions("need"), vectors.BLOCK_QUERIES, min), "needs")
    rest = rows.filter(length < cut).repartitionByRange(turns, F.desc("length"))
    rest = rest.sortWithinPartitions(F.desc(F.floor(F.log2(length) * CLASSES)), "cell", F.desc("length")).select("vec_id", "v", "length")
    found = vectors.met(rest, asked, False, Buckets, Search(k), reach=True)
    return vectors.ranked(best.select(found.columns).unionByName(found), k, False)
