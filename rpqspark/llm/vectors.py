"""What both searches share: vectors in blocks, queries against all blocks, the best of each.

Vectors travel as packed blocks of bounded size. Queries are packed likewise, and
each block of queries is copied to every part of the shuffled vectors, in which it meets
their blocks; nothing that grows with the table is broadcast or collected, and a task holds
a bounded group of queries. A pair of blocks gives at most k rows a query, and a ranking over those
picks the k best.

Vectors that are null, of another length than the query, or that hold a null or
a non-finite component take no part, nor do rows without an id. Repeated rows
are candidates of their own, except those with the query's own id.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import common

BLOCK_VECTORS, BLOCK_QUERIES = 2048, 256
#: Copies of the queries at most (they are a fiftieth of the vectors, or less), and their bytes that a task holds.
COPIES, HELD = 50, 64 << 20
_BLOCK = pa.schema([("dim", pa.int32()), ("first", pa.int64()), ("ids", pa.binary()), ("vectors", pa.binary()), ("extreme", pa.float64()), ("given", pa.binary())])
BLOCK = "dim int, first long, ids binary, vectors binary, extreme double, given binary"
#: Forms of packed components by their bytes.
FORMS = {2: np.int16, 8: np.float64}


def usable(table: DataFrame, vector: str, nonzero: bool) -> DataFrame:
    """(vec_id, v): rows that take part, vectors as doubles."""
    v = F.col("v")
    rows = table.select(F.col("vec_id").cast("long").alias("vec_id"), F.col(f"`{vector}`").cast("array<double>").alias("v"))
    good = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    rows = rows.filter(F.col("vec_id").isNotNull() & v.isNotNull() & (F.size(v) > 0) & good)
    return rows.filter(F.exists(v, lambda x: x != 0)) if nonzero else rows


def headed(vectors: np.ndarray) -> pa.Array:
    """Each row as binary: a byte that names its form, then its components."""
    n, dim = vectors.shape
    width = dim * vectors.itemsize + 1
    out = np.empty((n, width), np.uint8)
    out[:, 0], out[:, 1:] = vectors.itemsize, np.ascontiguousarray(vectors).view(np.uint8).reshape(n, width - 1)
    return pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer(np.arange(n + 1, dtype=np.int32) * np.int32(width)), pa.py_buffer(out)])


def _split(column: pa.Array):
    """(form, places, vectors) of the vectors of each form and length in a batch; lists hold doubles, binaries are ``headed``."""
    if not len(column):
        return
    if pa.types.is_binary(column.type):
        ends = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1]
        flat, starts, sizes = np.frombuffer(column.buffers()[2] or b"", np.uint8), ends[:-1], np.diff(ends)
        kinds = np.stack([sizes, flat[starts]], axis=1)
        for size, form in np.unique(kinds, axis=0).tolist():
            at = np.flatnonzero((kinds == (size, form)).all(axis=1))
            yield form, at, flat[(starts[at][:, None] + np.arange(1, size)).ravel()].view(FORMS[form]).reshape(len(at), -1)
    else:
        sizes = column.value_lengths().to_numpy()
        flat, ends = column.flatten().to_numpy(), np.cumsum(sizes)
        for dim in np.unique(sizes).tolist():
            at = np.flatnonzero(sizes == dim)
            yield 8, at, flat[((ends[at] - dim)[:, None] + np.arange(dim)).ravel()].reshape(-1, dim)


def blocks(rows: DataFrame, most: int, extreme: Callable = max) -> DataFrame:
    """Packed blocks of up to ``most`` vectors of one length and form, in the order of the rows.

    Vectors are lists of doubles or ``headed`` binaries. A third column of the rows, if there is one,
    gives each block its ``extreme``, and is packed beside as ``given`` (doubles).
    """

    def work(batches):
        have: dict[tuple, list] = {}

        def packed(dim, part):
            ids, vectors, own = (np.concatenate(x) for x in zip(*part))
            for i in range(0, len(ids), most):
                at = slice(i, i + most)
                yield common.batch(_BLOCK, [dim], [int(ids[i])], [ids[at].tobytes()], [vectors[at].tobytes()], [float(extreme(own[at]))], [own[at].tobytes() if third else b""])

        third = False
        for b in batches:
            ids, third = b.column(0).to_numpy(), b.num_columns > 2
            own = b.column(2).to_numpy(zero_copy_only=False) if third else np.zeros(len(ids))
            for form, at, vectors in _split(b.column(1)):
                kind = (form, vectors.shape[1])
                have.setdefault(kind, []).append((ids[at], vectors, own[at]))
                if sum(len(x[0]) for x in have[kind]) >= most:
                    yield from packed(kind[1], have.pop(kind))
        for kind, part in have.items():
            yield from packed(kind[1], part)

    return rows.mapInArrow(work, BLOCK)


def packed_queries(rows: DataFrame, every: int, stage: common.Stage) -> DataFrame:
    """The stored blocks of rows whose id ``every`` divides."""
    return stage.save(blocks(rows.filter(F.pmod("vec_id", F.lit(every)) == 0), BLOCK_QUERIES), "queries")


def met(rows: DataFrame, asked: DataFrame, nearest: bool, prepare: Callable, find: Callable, reach: bool = False) -> DataFrame:
    """(query_id, vec_id, score, approx) of what blocks of rows give to blocks of queries.

    ``prepare(ids, vectors)`` is called once for a block and all query blocks that it
    meets in a task; ``find(prepared, query ids, query vectors)`` gives arrays (query id, vec_id,
    score, approx); the score is exact or null, approx orders scores that are null. A find that has a
    ``start(query ids, query vectors, given)`` keeps what that returns for a block of queries: its ``meet(prepared,
    kept)`` gives such arrays or None, and the kept one's ``given()`` those of all blocks of the task.
    ``reach``: only pairs meet whose block has an extreme as large as that of the query block.

    Both sides are dealt to the same parts by number: a block of vectors to one turn, a block of
    queries to all turns. Queries of more than ``HELD`` bytes are dealt into groups,
    each of which every block of vectors meets in a part of its own.
    """
    spark = rows.sparkSession
    keeps = hasattr(find, "start")
    turns = min(common.partitions(spark), COPIES, find.turns if keeps else COPIES)
    common.small_batches(spark, 512 if keeps else 4096)
    size = asked.agg(F.sum(F.length("vectors"))).first()[0] or 0
    groups = -(-size // HELD) or 1
    whole = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    row = F.monotonically_increasing_id()
    # Blocks follow each other in a partition, so that turns and groups are dealt evenly.
    dealt = lambda n: F.pmod(F.shiftright(row, 33) + row.bitwiseAND(F.lit((1 << 33) - 1)), F.lit(n)).cast("int")
    names = ["part", "own", "dim", "ids", "vectors", "extreme"] + ["given"] * keeps
    own = blocks(rows, BLOCK_VECTORS).withColumn("turn", dealt(turns)).withColumn("group", whole(groups))
    asked = asked.withColumn("group", dealt(groups)).withColumn("turn", whole(turns))
    own, asked = (x.withColumns({"part": F.col("turn") * groups + F.col("group"), "own": F.lit(k)}).select(names) for k, x in ((True, own), (False, asked)))
    parts = asked.unionByName(own).repartitionById(turns * groups, F.col("part")).sortWithinPartitions("own")
    kind = "double" if nearest else "long"
    schema = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.float64() if nearest else pa.int64()), ("approx", pa.float64())])

    def work(batches):
        held: list = []
        for b in batches:
            for mine, dim, ids, packed, extreme, *given in zip(*b.columns):
                dim, extreme = dim.as_py(), extreme.as_py()
                ids, packed = np.frombuffer(ids.as_py(), np.int64), packed.as_py()
                at = np.frombuffer(packed, FORMS[len(packed) // (len(ids) * dim)]).reshape(-1, dim)
                if not mine.as_py():
                    least = np.frombuffer(given[0].as_py()) if reach and keeps else None
                    held.append((dim, (find.start(ids, at, least),) if keeps else (ids, at), extreme))
                    continue
                # The margin only lets more pairs meet: lengths are rounded.
                meets = [q for d, q, x in held if d == dim and (not reach or extreme * (1 + 1e-9) + 1e-6 >= x)]
                prepared = prepare(ids, at) if meets else None
                for q in meets:
                    found = (find.meet if keeps else find)(prepared, *q)
                    if found is not None:
                        yield common.batch(schema, *found)
        for _, q, _ in held if keeps else ():
            yield common.batch(schema, *q[0].given())

    return parts.select(names[1:]).mapInArrow(work, f"query_id long, vec_id long, score {kind}, approx double")


def ranked(found: DataFrame, k: int, nearest: bool, *more: str) -> DataFrame:
    """(query_id, rank, vec_id, score, more columns) of the k best of each query."""
    order = [F.col("score").asc()] if nearest else [F.col("approx").desc(), F.col("score").desc()]
    rows = found.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy(*order, F.col("vec_id"))))
    return rows.filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score", *more)
