"""Connected components of a link table, by alternating star contraction.

Each partition first contracts its own links (so a dense group enters as a star),
then rounds of two joins run until the links are stars: every node is
tied to the smallest node among its neighbours. Rounds are written to the
shared folder. Hubs are pre-aggregated before the shuffle, and the joins back
are plain equi-joins that adaptive execution can split.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

_LINKS = pa.schema([("a", pa.int64()), ("b", pa.int64())])


def find(parent: dict, x: int) -> int:
    root = x
    while (up := parent.get(root, root)) != root:
        root = up
    while x != root:
        parent[x], x = root, parent.get(x, root)
    return root


def forest(batches):
    """Links of a partition to (node, smallest node of its local component)."""
    parent: dict[int, int] = {}
    for b in batches:
        for x, y in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
            x, y = find(parent, x), find(parent, y)
            if x != y:
                parent[max(x, y)] = min(x, y)
                parent.setdefault(min(x, y), min(x, y))
    rows = [(x, r) for x in list(parent) if (r := find(parent, x)) != x]
    for i in range(0, len(rows), 10_000):
        a, b = zip(*rows[i : i + 10_000])
        yield common.batch(_LINKS, a, b)


def _large(e: DataFrame) -> DataFrame:
    """Larger neighbours of each node go to the smallest of its neighbourhood."""
    both = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
    return both.join(least, "a").filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))


def _small(e: DataFrame) -> DataFrame:
    """Smaller neighbours of each node, and the node, go to the smallest of them."""
    down = e.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    least = down.groupBy("a").agg(F.min("b").alias("m"))
    moved = down.join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b")
    return moved.unionByName(least.select("a", F.col("m").alias("b"))).distinct()


def components(links: DataFrame, stage: common.Stage, most_rounds: int = 60) -> DataFrame:
    """(node, root) of every node that has a link; the root is the smallest node.

    ``links``: columns a, b (long, not null, a <> b).
    """
    edges = stage.save(links.mapInArrow(forest, "a long, b long").distinct(), "links0")
    seen = None
    for k in range(1, most_rounds):
        edges = stage.save(_small(_large(edges)), f"links{k}")
        state = edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if k > 1:
            stage.drop(f"links{k - 1}")
        if state == seen:
            break
        seen = state
    else:
        raise RuntimeError("links did not contract")
    return edges.select(F.col("a").alias("node"), F.col("b").alias("root"))
