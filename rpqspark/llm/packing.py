"""Best-fit packing of token sequences by minimum bin slack.

Documents become token ids; those over the capacity are cut. A bin is filled by
its longest open piece and the fullest combination of others: the sums that
the available lengths can reach are the bits of one integer, each length shifts
it, and walking back from the highest bit gives the members, which are removed.

Pieces are dealt into groups of bounded size that are packed apart, so no task
sees the whole table; a group wastes less than one bin, which is under
1/2000 of it at the default size. Only (id, piece, length, checksum) rows are
shuffled, never texts. Nulls count as empty text; every document has one piece
at least; repeated rows are packed as rows of their own.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import bpe, common

#: Pieces that are packed together.
GROUP_PIECES = 20_000

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


class Encoder:
    """Texts to little-endian unsigned 32-bit ids, as bytes.

    In byte-level vocabularies whose merges are numbered in the order of their
    ids, the id of a token is its rank, so words new to the table go to a compiled
    merge loop; other vocabularies merge by :class:`bpe.Bpe`.
    """

    def __init__(self, path: str):
        self.bpe = own = bpe.load(path)
        as_bytes = lambda ids: np.array(ids, "<u4").tobytes()
        make = own.word
        if not own.suffix and all(new == rank + 256 for rank, new in own.merge.values()):
            import tiktoken

            back = {c: b for b, c in enumerate(own.to_char)}
            ranks = {bytes(map(back.__getitem__, t)): i for t, i in own.vocab.items() if t not in own.special}
            core = tiktoken.Encoding("byte level", pat_str=".", mergeable_ranks=ranks, special_tokens={})._core_bpe.encode_single_piece
            self.own = bpe.Finished(lambda w: as_bytes(core(w.encode())))
        else:
            self.own = bpe.Finished(lambda w: as_bytes(make(own.spelled(w))))
        self.raw = bpe.Finished(lambda w: as_bytes(make(w)))

    def __call__(self, text: str | None) -> bytes:
        out = []
        for s in self.bpe.spans(text or ""):
            if s in self.bpe.special:
                out.append(np.array([self.bpe.special[s]], "<u4").tobytes())
                continue
            found, is_spelled = self.bpe.pieces(s)
            table = self.raw if is_spelled else self.own
            out.append(b"".join(map(table.__getitem__, found)))
        return b"".join(out)


def cut(n: int, capacity: int) -> list[tuple[int, int]]:
    """(start, length) of the pieces of n ids; only the first may be shorter."""
    if n <= capacity:
        return [(0, n)]
    first = n % capacity or capacity
    return [(0, first)] + [(s, capacity) for s in range(first, n, capacity)]


def pieces(docs: DataFrame, tokenizer: str, capacity: int, end_id: int = 0) -> DataFrame:
    """Pieces of every document, with their ids' checksum."""

    def work(batches):
        encode, end = Encoder(tokenizer), end_id.to_bytes(4, "little")
        schema = pa.schema([("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64())])
        for b in batches:
            rows = []
            for i, text in zip(b.column(0), b.column(1)):
                ids, i = encode(text.as_py()) + end, i.as_py()
                rows += [(i, k, s, n, zlib.crc32(ids[4 * s : 4 * (s + n)])) for k, (s, n) in enumerate(cut(len(ids) // 4, capacity))]
            yield common.batch(schema, *zip(*rows)) if rows else common.batch(schema, [], [], [], [], [])

    return common.columns(docs, ["doc_id", "text"]).mapInArrow(work, PIECES)


def fill(lengths: list[int], counts: dict[int, int], room: int) -> list[int]:
    """Lengths (a multiset bounded by counts) with the largest sum up to room.

    ``lengths``: those available, longest first.
    """
    full, mask = 1 << room, (1 << (room + 1)) - 1
    steps, reach, taken = [], 1, 0
    for n in lengths:
        if n > room:
            continue
        for _ in range(min(counts[n], room // n)):
            grown = (reach | reach << n) & mask
            if grown == reach:
                break
            steps.append((n, reach))
            reach = grown
            taken += 1
        if reach & full:
            break
    at, out = reach.bit_length() - 1, []
    for n, before in reversed(steps):
        if not before >> at & 1:
            out.append(n)
            at -= n
    return out


def pack(lengths: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """Bin number and offset of each length."""
    order = np.argsort(-lengths, kind="stable")
    by: dict[int, list[int]] = {}
    for i in order[::-1].tolist():
        by.setdefault(int(lengths[i]), []).append(i)
    counts = {n: len(v) for n, v in by.items()}
    open_ = sorted(by, reverse=True)
    bins, offsets, k = np.zeros(len(lengths), np.int64), np.zeros(len(lengths), np.int64), 0
    while open_:
        longest = open_[0]
        chosen, room = [longest], capacity - longest
        counts[longest] -= 1
        if room > 0:
            chosen += fill([n for n in open_ if n <= room and counts[n]], counts, room)
            for n in chosen[1:]:
                counts[n] -= 1
        at = 0
        for n in chosen:
            i = by[n].pop()
            bins[i], offsets[i] = k, at
            at += n
        k += 1
        if any(not counts[n] for n in chosen):
            open_ = [n for n in open_ if counts[n]]
    return bins, offsets


def best_fit(docs: DataFrame, tokenizer: str, capacity: int = 2048, end_id: int = 0, group_pieces: int = GROUP_PIECES) -> DataFrame:
    """One row per piece: its sequence and its place there.

    The groups come from a hash of (doc_id, piece, checksum), so a hot source or
    a group of copies is spread; their number follows the number of pieces.
    """
    spark = docs.sparkSession
    common.small_batches(spark)
    stage = common.Stage(spark, "packing")
    table = stage.save(pieces(docs, tokenizer, capacity, end_id), "pieces")
    # A full piece is a sequence by itself and needs no group.
    loose = table.filter(F.col("length") < capacity)
    groups = max(1, -(-loose.count() // group_pieces))
    key = F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32", "start"), F.lit(groups))

    def work(key, t):
        t = t.sort_by([("length", "descending"), ("doc_id", "ascending"), ("piece", "ascending"), ("ids_crc32", "ascending")])
        bins, offsets = pack(t.column("length").to_numpy(), capacity)
        return t.drop_columns(["_group"]).append_column("sequence_id", pa.array(bins * groups + key[0].as_py())).append_column("offset", pa.array(offsets))

    packed = loose.withColumn("_group", key).groupBy("_group").applyInArrow(work, f"{PIECES}, sequence_id long, offset long")
    # Negative numbers: distinct from the groups' own, and apart by document and piece.
    alone = table.filter(F.col("length") >= capacity).withColumn("sequence_id", -1 - F.monotonically_increasing_id()).withColumn("offset", F.lit(0).cast("long"))
    return packed.unionByName(alone)
