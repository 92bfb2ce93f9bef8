"""Approximate nearest neighbours by collision-counting hashing.

Every block is indexed once, for all queries that it meets, by ``projections`` random
directions, each an array of projected values in order. A query opens a window around its own projection
in each array; a vector collides where it lies inside. Virtual rehashing widens the
windows step by step and only counts what each step adds. Vectors that collide in
``share`` of the arrays or more are verified by their exact distance; no limit is set
on their number. A query is done with a block once k verified vectors lie well
inside the reach of its windows, or all of the block was verified. A lower share than all
can be asked for (``verified``), which ends searches sooner and may miss more; the queries
here do not.

A vector at distance d falls into a window of half-width R with probability
P(|z| < R / d), 0.68 at d = R; ``share`` lies under that, so that vectors within R
pass with high probability and those far outside seldom do.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame

from . import common, vectors

PROJECTIONS, SHARE, FIRST, GROWTH, INSIDE = 96, 0.6, 0.6, 1.2, 1.08


class Index:
    """The sorted projections of one block."""

    def __init__(self, ids: np.ndarray, base: np.ndarray, projections: int = PROJECTIONS, seed: int = 11):
        self.ids, self.base = ids, base
        self.directions = np.random.default_rng([seed, base.shape[1]]).standard_normal((base.shape[1], projections))
        at = base @ self.directions
        order = np.argsort(at, axis=0)
        self.lines = np.ascontiguousarray(np.take_along_axis(at, order, axis=0).T)
        self.order = np.ascontiguousarray(order.T.astype(np.int32))
        self.spread = float(np.median(np.std(at, axis=0))) * 2**0.5 or 1.0
        self.furthest = float(np.abs(at).max())


def collisions(index: Index, q_ids, queries, k: int = 10, verified: float = 1.0):
    """The k nearest found in one block, of each query."""
    ids, base, order = index.ids, index.base, index.order
    n, asked = len(ids), queries @ index.directions
    furthest = max(index.furthest, float(np.abs(asked).max())) * 2 + 1e-9
    need = int(np.ceil(SHARE * len(index.lines)))
    out: list = [[], [], []]
    levels = [FIRST * index.spread]
    while levels[-1] < furthest:
        levels.append(levels[-1] * (GROWTH if len(levels) < 8 else 4))
    lows = np.stack([[np.searchsorted(line, asked[:, i] - r) for i, line in enumerate(index.lines)] for r in levels], axis=-1)
    highs = np.stack([[np.searchsorted(line, asked[:, i] + r, side="right") for i, line in enumerate(index.lines)] for r in levels], axis=-1)
    for j in range(len(queries)):
        counts, done = np.zeros(n, np.int64), np.zeros(n, bool)
        best_d, best_i = np.empty(0), np.empty(0, np.int64)
        low, high = lows[:, j], highs[:, j]
        for level, reach in enumerate(levels):
            lo, hi = low[:, level].tolist(), high[:, level].tolist()
            if level == 0:
                parts = [o[a:b] for o, a, b in zip(order, lo, hi)]
            else:
                was_lo, was_hi = low[:, level - 1].tolist(), high[:, level - 1].tolist()
                parts = [o[a:b] for o, a, b in zip(order, lo, was_lo)] + [o[a:b] for o, a, b in zip(order, was_hi, hi)]
            counts += np.bincount(np.concatenate(parts), minlength=n)
            fresh = np.flatnonzero((counts >= need) & ~done)
            if len(fresh):
                done[fresh] = True
                fresh = fresh[ids[fresh] != q_ids[j]]
                d = np.sqrt(((base[fresh] - queries[j]) ** 2).sum(axis=1))
                best_d, best_i = np.concatenate([best_d, d]), np.concatenate([best_i, ids[fresh]])
                if len(best_d) > k:
                    # All that tie with the k-th stay until the order decides.
                    keep = best_d <= np.partition(best_d, k - 1)[k - 1]
                    best_d, best_i = best_d[keep], best_i[keep]
                    top = np.lexsort((best_i, best_d))[:k]
                    best_d, best_i = best_d[top], best_i[top]
            if len(best_d) >= k and (best_d[-1] * INSIDE <= reach or done.sum() >= verified * n):
                break
        top = np.lexsort((best_i, best_d))[:k]
        out[0].append(np.full(len(top), q_ids[j]))
        out[1].append(best_i[top])
        out[2].append(best_d[top])
    return tuple(np.concatenate(x) for x in out)


def nearest(table: DataFrame, vector: str = "embedding", every: int = 100, k: int = 10, projections: int = PROJECTIONS, verified: float = 1.0) -> DataFrame:
    """The k nearest found by Euclidean distance of every row whose vec_id ``every`` divides.

    Zero vectors take no part, nor do those named in ``vectors``. An empty table, or one
    without queries, gives an empty one; vectors at equal distances come by vec_id.
    """

    stage = common.Stage(table.sparkSession, "neighbours")
    rows = vectors.usable(table, vector, True)
    common.small_batches(table.sparkSession, 4096)

    def find(index, q_ids, queries):
        q, i, d = collisions(index, q_ids, queries, k, verified)
        return q, i, d, d

    found = vectors.met(rows, vectors.packed_queries(rows, every, stage), True, lambda ids, base: Index(ids, base, projections), find)
    return vectors.ranked(found, k, True)
