"""Near-duplicate groups of documents by SimHash, with pigeonring filtering.

Fingerprints: words are runs of bytes other than ASCII white space, A-Z lower
case; every 3-word shingle counts as often as it occurs; a bit of the
fingerprint is 1 if it is set in over half of the shingles' XXH64 hashes.

Links: fingerprints that differ in at most ``distance`` = 3 bits. The 64 bits are
a ring of four segments of 16. By the pigeonring principle two linked
fingerprints have a start from which the first segment differs in at most
floor(3/4) = 0 bits, the first two together in at most floor(6/4) = 1, the first
three in at most floor(9/4) = 2, all four in at most 3. The first two budgets
make 32-bit keys (equal segment, and a neighbour with at most one bit flipped),
so rows meet by an equi-join; the third prunes what met, and only then the full
Hamming distance is taken.

Equal fingerprints are one node from the start, so copies cost nothing. Each bucket
of the join is cut to links that a forest needs, so that a group of n
near copies gives about n links and not n*n/2.

``near_groups`` is for texts that are alike and not only nearly equal: shingles of five
words, each counted once, and a similarity (shared shingles over all) of 0.8 or more. There two fingerprints
of 64 bits differ in about ten, of which no index on segments is selective. So fingerprints
have 256 bits there, candidates come from keys of smallest hashes (24 keys of 6 each, which
miss a pair at 0.8 once in 1,500 times), pigeonring chains over 16 segments prune them
before the full Hamming distance, at most ``NEAR`` = 52 (39 are expected at 0.8), and the
pairs left are held against their shingles.

Null text has no words (fingerprint zero, linked like any other); repeated rows
are rows of their own; an empty table gives an empty one; a null doc_id takes
part but cannot name a component unless it is alone in it.
"""

from __future__ import annotations

from itertools import repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common
from .anchors import mix
from .components import components

SEED, SEGMENTS, WIDTH, DISTANCE = 42, 4, 16, 3
_BITS = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1)[:, ::-1].astype(np.int64)


def fingerprint(text: bytes) -> int:
    """Unsigned fingerprint of a UTF-8 text."""
    words = text.lower().split()
    if not words:
        return 0
    n = max(1, len(words) - 2)
    shingles = map(b" ".join, zip(words, words[1:], words[2:])) if len(words) >= 3 else [b" ".join(words)]
    hashes = np.fromiter(map(xxhash.xxh64_intdigest, shingles, repeat(SEED)), np.uint64, n)
    counts = np.concatenate([np.bincount(column, minlength=256) @ _BITS for column in hashes.astype("<u8").view(np.uint8).reshape(n, 8).T])
    return int.from_bytes(np.packbits(counts * 2 > n, bitorder="little").tobytes(), "little")


def fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, fp): the fingerprint as a signed 64-bit integer."""
    common.small_batches(docs.sparkSession)
    schema = pa.schema([("doc_id", pa.int64()), ("fp", pa.int64())])

    def work(batches):
        for b in batches:
            made = np.array([fingerprint((t.as_py() or "").encode()) for t in b.column(1)], np.uint64)
            yield common.batch(schema, b.column(0), made.view(np.int64))

    return common.columns(docs, ["doc_id", "text"]).mapInArrow(work, "doc_id long, fp long")


def _key(fp: Column, turn: int) -> Column:
    """The 32 bits of segments ``turn`` and ``turn + 1`` of the ring, the first on top."""
    shift = WIDTH * turn
    turned = fp if not shift else F.shiftleft(fp, shift).bitwiseOR(F.shiftrightunsigned(fp, 64 - shift))
    return F.shiftrightunsigned(turned, 32)


def keyed(nodes: DataFrame) -> DataFrame:
    """Rows (k, probe, fp): each node's four own keys, and the keys it looks under.

    The second segment may differ in one bit, so a node looks under 17 keys a turn.
    """
    flips = F.array(*[F.lit(0).cast("long")] + [F.lit(1 << b).cast("long") for b in range(WIDTH)])
    keys = F.array(*[F.struct(F.lit(t).alias("t"), _key(F.col("fp"), t).alias("k")) for t in range(SEGMENTS)])
    own = nodes.select("fp", F.explode(keys).alias("key")).select("fp", F.shiftleft(F.col("key.t").cast("long"), 32).bitwiseOR(F.col("key.k")).alias("k"))
    looked = own.select("fp", "k", F.explode(flips).alias("flip")).select(F.col("k").bitwiseXOR(F.col("flip")).alias("k"), F.lit(1).cast("byte").alias("probe"), "fp")
    return own.select("k", F.lit(0).cast("byte").alias("probe"), "fp").unionByName(looked)


def _bucket(turn: int, own: np.ndarray, looked: np.ndarray, out: list) -> None:
    """Links of a bucket between own and looked-under nodes, cut to a forest.

    Blocks bound the memory; at most one link a node pair of components is kept.
    """
    third = np.uint64(((1 << 48) - 1) << 16)
    rot = lambda x: x << np.uint64(WIDTH * turn) | x >> np.uint64(64 - WIDTH * turn) if turn else x
    group, n_groups = np.full(len(looked), -1, np.int64), 0
    chosen: list[int] = []
    for f in own:
        x = rot(looked ^ f)
        near = np.flatnonzero((np.bitwise_count(x & third) <= 2) & (np.bitwise_count(x) <= DISTANCE) & (x != 0))
        if not len(near):
            continue
        parts, at = np.unique(group[near], return_index=True)
        fresh = near[group[near] == -1]
        ends = looked[np.concatenate([fresh, near[at[parts >= 0]]])]
        chosen += ends.view(np.int64).tolist()
        out[0] += [int(f.view(np.int64))] * len(ends)
        parts = parts[parts >= 0]
        if len(parts):
            group[np.isin(group, parts)] = n_groups
        group[fresh] = n_groups
        n_groups += 1
    out[1] += chosen


def _met(batches):
    """Rows sorted by (k, probe) to links; a bucket may run over several batches."""
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])
    rest = [np.empty(0, np.int64), np.empty(0, np.int8), np.empty(0, np.uint64)]

    def done(k, probe, fp):
        """Buckets that hold more than a node and its own look."""
        cuts = np.flatnonzero(np.diff(k)) + 1
        starts, ends = np.concatenate([[0], cuts]), np.concatenate([cuts, [len(k)]])
        own = np.add.reduceat((probe == 0).astype(np.int64), starts)
        size = ends - starts
        out: list = [[], []]
        for i in np.flatnonzero((own > 0) & (size > own) & (size > 2)):
            s, m, e = starts[i], starts[i] + own[i], ends[i]
            _bucket(int(k[s] >> 32), fp[s:m], fp[m:e], out)
        return out

    for b in batches:
        k, probe, fp = (np.concatenate([r, b.column(i).to_numpy(zero_copy_only=False).astype(r.dtype, copy=False) if i < 2 else b.column(i).to_numpy().view(np.uint64)]) for i, r in enumerate(rest))
        last = np.searchsorted(k, k[-1])
        if last:
            a, c = done(k[:last], probe[:last], fp[:last])
            if a:
                yield common.batch(schema, a, c)
        rest = [k[last:], probe[last:], fp[last:]]
    if len(rest[0]):
        a, c = done(*rest)
        if a:
            yield common.batch(schema, a, c)


def links(nodes: DataFrame) -> DataFrame:
    """(a, b): links of distinct fingerprints, whose closure equals that of all links."""
    n = common.partitions(nodes.sparkSession)
    return keyed(nodes).repartition(n, "k").sortWithinPartitions("k", "probe").mapInArrow(_met, "a long, b long")


def groups(docs: DataFrame) -> DataFrame:
    """(doc_id, fingerprint, component_id) of every row of docs."""
    spark = docs.sparkSession
    stage = common.Stage(spark, "simhash")
    prints = stage.save(fingerprints(docs), "prints")
    nodes = stage.save(prints.groupBy("fp").agg(F.min("doc_id").alias("doc")), "nodes")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "50000")
    roots = components(links(nodes.select("fp")), stage)
    common.small_batches(spark)
    named = nodes.join(roots, nodes.fp == roots.node, "left").select("fp", "doc", F.coalesce("root", "fp").alias("root"))
    least = named.groupBy("root").agg(F.min("doc").alias("component_id"))
    of = stage.save(named.join(least, "root").select("fp", "component_id"), "of")
    return prints.join(of, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


WORDS, SIMILARITY, NEAR_BITS, NEAR, NEAR_SEGMENTS, BANDS, ROWS = 5, 0.8, 256, 52, 16, 24, 6
#: Nodes (16 bytes each) that are broadcast at most; more go by a shuffle.
SENT = 500_000
_LANES = mix(np.arange(1, NEAR_BITS // 64 + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
_BINS = BANDS * ROWS
#: Where an empty bin borrows from: the same places, in the same order, for every text.
_BORROW = np.random.default_rng(3).integers(0, _BINS, (64, _BINS))
_ODD = np.random.default_rng(4).integers(0, 1 << 62, ROWS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_LEAST = np.uint64(2**64 - 1)


def shingles(text: bytes, words: int = WORDS) -> np.ndarray:
    """Sorted distinct hashes of a text's shingles (fewer words: the whole sequence; none: none)."""
    have = text.lower().split()
    if not have:
        return np.empty(0, np.uint64)
    n = max(1, len(have) - words + 1)
    parts = map(b" ".join, zip(*(have[i:] for i in range(words)))) if len(have) >= words else [b" ".join(have)]
    hashes = np.sort(np.fromiter(map(xxhash.xxh64_intdigest, parts, repeat(SEED)), np.uint64, n))
    return hashes[np.concatenate([[True], hashes[1:] != hashes[:-1]])]


def sketch(hashes: np.ndarray) -> tuple[int, np.ndarray, np.ndarray]:
    """Of a set of shingles: a hash of the whole set, its fingerprint of 256 bits, its keys."""
    n = len(hashes)
    if not n:
        return 0, np.zeros(NEAR_BITS // 64, np.uint64), np.zeros(BANDS, np.uint64)
    counts = np.zeros(NEAR_BITS, np.int64)
    for i in range(0, n, 1 << 14):
        lanes = mix(hashes[i : i + (1 << 14), None] ^ _LANES)
        counts += np.unpackbits(lanes.view(np.uint8).reshape(len(lanes), -1), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bins = np.full(_BINS, _LEAST)
    np.minimum.at(bins, ((hashes >> np.uint64(32)) * np.uint64(_BINS) >> np.uint64(32)).astype(np.int64), mix(hashes))
    empty = np.flatnonzero(bins == _LEAST)
    own = bins.copy()
    for turn in _BORROW:
        if not len(empty):
            break
        bins[empty] = own[turn[empty]]
        empty = empty[bins[empty] == _LEAST]
    if len(empty):
        bins[empty] = own.min()
    keys = mix((bins.reshape(BANDS, ROWS) * _ODD).sum(axis=1, dtype=np.uint64) + mix(np.arange(BANDS, dtype=np.uint64)))
    return xxhash.xxh64_intdigest(hashes.tobytes(), SEED), np.packbits(counts * 2 > n, bitorder="little").view(np.uint64), keys


def near(fp: np.ndarray, others: np.ndarray, distance: int = NEAR) -> np.ndarray:
    """Which of the others are within the distance: a chain of segments within its budgets first, then all bits."""
    width = NEAR_BITS // NEAR_SEGMENTS
    apart = np.bitwise_count((others ^ fp).view(f"<u{width // 8}")).astype(np.int16)
    # A start from which one segment, then two, are within their shares of the distance.
    one = apart <= distance // NEAR_SEGMENTS
    two = apart + np.roll(apart, -1, axis=1) <= 2 * distance // NEAR_SEGMENTS
    may = np.flatnonzero((one & two).any(axis=1))
    return may[apart[may].sum(axis=1) <= distance]


def _near_bucket(nodes: np.ndarray, fps: np.ndarray, out: list) -> None:
    """Links of a bucket, as a forest with the closure of all its links.

    Each node is compared with those only that no link reaches yet, so a bucket of n
    alike takes about n steps.
    """
    left = np.arange(len(nodes))
    while len(left):
        todo, left = [int(left[0])], left[1:]
        while todo and len(left):
            i = todo.pop()
            hit = near(fps[i], fps[left])
            if len(hit):
                ends = left[hit]
                out[0] += [int(nodes[i])] * len(ends)
                out[1] += nodes[ends].tolist()
                todo += ends.tolist()
                left = np.delete(left, hit)


_LANE_NAMES = [f"f{i}" for i in range(NEAR_BITS // 64)]


def _near_met(batches):
    """Rows (k, node, lanes) sorted by key to links; a bucket may run over several batches."""
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])
    rest = None

    def done(k, nodes, fps):
        starts = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]]))
        ends = np.concatenate([starts[1:], [len(k)]])
        out: list = [[], []]
        for i in np.flatnonzero(ends - starts > 1):
            _near_bucket(nodes[starts[i] : ends[i]], fps[starts[i] : ends[i]], out)
        if out[0]:
            yield common.batch(schema, *out)

    for b in batches:
        if not b.num_rows:
            continue
        t = [b.column(0).to_numpy(), b.column(1).to_numpy(), np.stack([b.column(i).to_numpy().view(np.uint64) for i in range(2, 2 + len(_LANE_NAMES))], axis=1)]
        rest = t if rest is None else [np.concatenate(x) for x in zip(rest, t)]
        last = int(np.searchsorted(rest[0], rest[0][-1]))
        if last:
            yield from done(*(x[:last] for x in rest))
            rest = [x[last:] for x in rest]
    if rest is not None:
        yield from done(*rest)


def _alike(similarity: float):
    """Pairs with both sets of shingles to those that are similar enough."""

    def work(batches):
        for b in batches:
            keep = []
            for x, y in zip(b.column(2), b.column(3)):
                x, y = np.frombuffer(x.as_buffer(), "<u4"), np.frombuffer(y.as_buffer(), "<u4")
                shared = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(shared >= similarity * (len(x) + len(y) - shared))
            yield b.select([0, 1]).filter(pa.array(keep, pa.bool_()))

    return work


def near_groups(docs: DataFrame, stage: common.Stage, words: int = WORDS, similarity: float = SIMILARITY) -> DataFrame:
    """(key1, key2, doc_id, root) of every row of docs: hashes of the whole row, and its group.

    Equal sets of shingles are one node. Null text has no words; texts without words are one group.
    """
    spark = docs.sparkSession
    lanes = ", ".join(f"{f} long" for f in _LANE_NAMES)
    schema = pa.schema([("key1", pa.int64()), ("key2", pa.int64()), ("doc_id", pa.int64()), ("node", pa.int64()), *[(f, pa.int64()) for f in _LANE_NAMES], ("keys", pa.binary()), ("parts", pa.binary())])

    def work(batches):
        for b in batches:
            sets = [shingles((t.as_py() or "").encode(), words) for t in b.column(3)]
            if sets:
                node, fps, keys = zip(*map(sketch, sets))
                fps = np.array(fps).view(np.int64)
                parts = [np.unique((s >> np.uint64(16)).astype("<u4")).tobytes() for s in sets]
                yield common.batch(schema, b.column(0), b.column(1), b.column(2), np.array(node, np.uint64).view(np.int64), *fps.T.copy(), [k.tobytes() for k in keys], parts)

    def unpacked(batches):
        out = pa.schema([("k", pa.int64()), ("node", pa.int64()), *[(f, pa.int64()) for f in _LANE_NAMES]])
        for b in batches:
            if b.num_rows:
                keys = np.frombuffer(b"".join(b.column(b.num_columns - 1).to_pylist()), np.int64)
                yield common.batch(out, keys, *(np.repeat(b.column(i).to_numpy(), BANDS) for i in range(b.num_columns - 1)))

    common.small_batches(spark)
    prints = stage.save(_keyed_rows(docs).select("key1", "key2", "doc_id", "text").mapInArrow(work, f"key1 long, key2 long, doc_id long, node long, {lanes}, keys binary, parts binary"), "prints")
    common.small_batches(spark, 4096)
    nodes = prints.groupBy("node").agg(*[F.first(f).alias(f) for f in _LANE_NAMES], F.first("keys").alias("keys"))
    keyed = nodes.mapInArrow(unpacked, f"k long, node long, {lanes}")
    found = keyed.repartition(common.partitions(spark), "k").sortWithinPartitions("k").mapInArrow(_near_met, "a long, b long")
    pairs = stage.save(found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "pairs")
    ends = stage.save(pairs.select(F.col("a").alias("node")).union(pairs.select("b")).distinct(), "ends")
    ends = F.broadcast(ends) if ends.count() <= SENT else ends
    sets = stage.save(prints.select("node", "parts").join(ends, "node").groupBy("node").agg(F.first("parts").alias("parts")), "sets")
    both = pairs.join(sets.select(F.col("node").alias("a"), F.col("parts").alias("x")), "a").join(sets.select(F.col("node").alias("b"), F.col("parts").alias("y")), "b")
    links = both.select("a", "b", "x", "y").mapInArrow(_alike(similarity), "a long, b long")
    roots = components(links, stage).withColumnRenamed("node", "of")
    common.small_batches(spark)
    return prints.join(roots, F.col("node") == F.col("of"), "left").select("key1", "key2", "doc_id", F.coalesce("root", "node").alias("root"))


def _keyed_rows(docs: DataFrame) -> DataFrame:
    """doc_id, text and two hashes of the whole row; columns that cannot be hashed do not count."""
    own = [F.col(f"`{f.name}`") for f in docs.schema.fields if "map" not in f.dataType.simpleString() and "variant" not in f.dataType.simpleString()]
    return docs.select(F.xxhash64(*own).alias("key1"), F.xxhash64(F.lit(1), *reversed(own)).alias("key2"), F.col("doc_id").cast("long").alias("doc_id"), "text")


def one_of_each(docs: DataFrame, words: int = WORDS) -> DataFrame:
    """docs with one row of each group of near duplicates (see ``near_groups``): the one with the smallest doc_id.

    Null ids come last; of rows that share an id the hash of the row decides, so repeated
    rows leave one, and different groups keep one row each whatever their ids. An empty
    table gives an empty one; all columns stay.
    """
    stage = common.Stage(docs.sparkSession, "simhash")
    of = near_groups(docs, stage, words)
    least = of.groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "key1", "key2")).alias("least"))
    chosen = stage.save(least.select("least.key1", "least.key2"), "chosen")
    names = docs.columns
    own = [F.col(f"`{f.name}`") for f in docs.schema.fields if "map" not in f.dataType.simpleString() and "variant" not in f.dataType.simpleString()]
    rows = docs.select(F.struct(*[F.col(f"`{n}`") for n in names]).alias("row"), F.xxhash64(*own).alias("key1"), F.xxhash64(F.lit(1), *reversed(own)).alias("key2"))
    return rows.join(chosen, ["key1", "key2"]).dropDuplicates(["key1", "key2"]).select("row.*")
