"""Space of the index and of plain triples."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph.encode import Encoded


def plain_bytes(n: int) -> int:
    """Three 32-bit numbers a triple."""
    return 12 * n


def packed_bytes(n: int, subjects: int, labels: int, objects: int) -> float:
    """Each part in as many bits as its universe needs."""
    return n * sum(max(1, math.ceil(math.log2(max(2, u)))) for u in (subjects, labels, objects)) / 8


def report(e: Encoded) -> DataFrame:
    """(component, bytes, bytes_per_edge): the two columns that path queries need and their
    counts over the completed graph, visited and label masks of 16 states, plain and packed triples.
    Sizes are those of plain bit vectors with a rank directory of one word in eight."""
    g = e.edges.agg(F.count("*").alias("n"), F.countDistinct("s").alias("s"), F.countDistinct("p").alias("p"), F.countDistinct("o").alias("o")).first()
    v = e.nodes.count()
    n2, p2 = 2 * g.n, 2 * g.p
    bits = lambda count, sigma: count * max(1, math.ceil(math.log2(max(2, sigma)))) * 1.125 / 8
    rows = [
        ("L_p", bits(n2, p2)), ("L_s", bits(n2, v)), ("C_o", 8.0 * (v + 1)), ("C_p", 8.0 * (p2 + 1)),
        ("visited masks", 2.0 * 2 * v), ("label masks", 2.0 * 2 * p2), ("plain triples", float(plain_bytes(g.n))), ("packed triples", packed_bytes(g.n, g.s, g.p, g.o)),
    ]
    out = e.edges.sparkSession.createDataFrame(rows, "component string, bytes double")
    return out.withColumn("bytes_per_edge", F.col("bytes") / F.lit(g.n))
