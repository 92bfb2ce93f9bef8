"""Suffix-array deduplication over bytes, by deep-shallow sorting.

Suffixes of a group (those behind one anchor gram, see ``anchors``) are sorted
by multikey quicksort down to a shallow depth. What is still equal there shares a
long prefix and goes to blind tries: a trie that keeps only the branching
bytes, so that a suffix is placed by one blind descent and one comparison.

A byte is removed if a string of ``size`` bytes covers it that also starts anywhere
else, in the same document too. Null text is empty; a repeated row is another
place; matches never cross documents.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import anchors, common

#: Bytes of a repeat, and of a passage: shorter repeats that are reported beside, and that
#: ``without_repeats`` cuts out (about fifty words, which are over 250 bytes).
SIZE, PASSAGE, PREFIX = 400, 250, 64
#: Depth in bytes at which quicksort hands over to blind tries.
SHALLOW = 24
_symbols = anchors.mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))


def byte_hashes(text: bytes) -> np.ndarray:
    return _symbols[np.frombuffer(text, np.uint8)]


def common_prefix(a: bytes, b: bytes, at: int = 0) -> int:
    """Length of the longest common prefix, known to be ``at`` or more."""
    n = min(len(a), len(b))
    if at < n and a[at] != b[at]:
        return at
    if a[at:n] == b[at:n]:
        return n
    step = 16
    while a[at : at + step] == b[at : at + step]:
        at += step
        step *= 2
    lo, hi = at, min(n, at + step)
    while hi - lo > 1:
        mid = (lo + hi) // 2
        if a[lo:mid] == b[lo:mid]:
            lo = mid
        else:
            hi = mid
    return lo


class _Branch:
    """An inner node: the depth of the byte that tells its children apart (-1: the end)."""

    __slots__ = ("depth", "children")

    def __init__(self, depth: int, children: dict):
        self.depth, self.children = depth, children


class BlindTrie:
    """Strings kept by branching bytes only; a leaf is a list of indices of equal strings."""

    def __init__(self, strings: list[bytes]):
        self.strings, self.root = strings, None

    def add(self, i: int) -> None:
        s = self.strings[i]
        if self.root is None:
            self.root = [i]
            return
        at = lambda text, depth: text[depth] if depth < len(text) else -1
        path, node = [], self.root
        while isinstance(node, _Branch):
            path.append(node)
            node = node.children.get(at(s, node.depth)) or next(iter(node.children.values()))
        other = self.strings[node[0]]
        depth = common_prefix(s, other)
        if depth == len(s) == len(other):
            node.append(i)
            return
        # The highest node at or below the depth is where the strings part.
        k = next((k for k, x in enumerate(path) if x.depth >= depth), len(path))
        below = path[k] if k < len(path) else node
        if isinstance(below, _Branch) and below.depth == depth:
            below.children[at(s, depth)] = [i]
            return
        branch = _Branch(depth, {at(other, depth): below, at(s, depth): [i]})
        if k:
            path[k - 1].children[at(s, path[k - 1].depth)] = branch
        else:
            self.root = branch

    def leaves(self) -> list[int]:
        out, stack = [], [self.root]
        while stack:
            node = stack.pop()
            if isinstance(node, _Branch):
                stack += [node.children[b] for b in sorted(node.children, reverse=True)]
            else:
                out += node
        return out


def deep_shallow(strings: list[bytes]) -> tuple[list[int], list[int]]:
    """Indices of the strings in order, and the common prefix of each with the one before."""
    order: list[int] = []
    todo = [(list(range(len(strings))), 0)]
    while todo:
        group, depth = todo.pop()
        if len(group) == 1:
            order += group
        elif depth >= SHALLOW or len(group) == 2:
            trie = BlindTrie(strings)
            for i in group:
                trie.add(i)
            order += trie.leaves()
        else:
            at = [strings[i][depth] if depth < len(strings[i]) else -1 for i in group]
            pivot = sorted((at[0], at[len(at) // 2], at[-1]))[1]
            less, equal, more = ([i for i, b in zip(group, at) if f(b)] for f in (pivot.__gt__, pivot.__eq__, pivot.__lt__))
            if more:
                todo.append((more, depth))
            if pivot == -1:
                order += equal  # strings that end here: nothing is smaller, all are equal
            elif equal:
                # What all of them share is passed in one step.
                first, ahead = strings[equal[0]], depth + 1
                while ahead < SHALLOW and ahead < len(first) and all(strings[i][ahead : ahead + 1] == first[ahead : ahead + 1] for i in equal):
                    ahead += 1
                todo.append((equal, ahead))
            if less:
                todo.append((less, depth))
    return order, [0] + [common_prefix(strings[i], strings[j]) for i, j in zip(order, order[1:])]


def rule(size: int, shorter: int = 0) -> anchors.Rule:
    return anchors.Rule(size, PREFIX, byte_hashes, bytes, lambda t, s, e: t[s:e], bytes, lambda x: anchors.Sorted(*deep_shallow(x)), common_prefix, earlier=False, shorter=shorter)


def _kept(text: bytes, spans) -> tuple[bytes, int]:
    starts, ends = anchors.union(spans)
    at, kept = 0, []
    for s, e in zip(starts.tolist(), ends.tolist()):
        kept.append(text[at:s])
        at = e
    return b"".join([*kept, text[at:]]), len(starts)


def repeated_bytes(docs: DataFrame, digest: bool = False, size: int = SIZE, passage: int = PASSAGE) -> DataFrame:
    """One row per document: doc_id, n_bytes, n_removed, n_spans, the kept bytes
    or, with ``digest``, their SHA-256, and n_passage: the bytes covered by repeats of
    ``passage`` bytes (0: not looked for, and null)."""
    keyed, spans = anchors.repeats(docs, rule(size, passage), "suffixes")
    last = ("kept_sha256", pa.string()) if digest else ("kept", pa.binary())
    schema = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), last, ("n_passage", pa.int64())])

    def work(batches):
        for b in batches:
            rows = []
            for text, spans in zip(b.column(1), b.column(2)):
                raw, spans = (text.as_py() or "").encode(), spans.as_py()
                kept, n = _kept(raw, spans)
                starts, ends = anchors.union(spans, anchors.SHORT_SPAN)
                rows.append((len(raw), len(raw) - len(kept), n, hashlib.sha256(kept).hexdigest() if digest else kept, int((ends - starts).sum()) if passage else None))
            yield common.batch(schema, b.column(0), *zip(*rows)) if rows else common.batch(schema, *[[]] * 6)

    return anchors.with_spans(keyed, spans).mapInArrow(work, f"doc_id long, n_bytes long, n_removed long, n_spans long, {last[0]} {'string' if digest else 'binary'}, n_passage long")


def without_repeats(docs: DataFrame, size: int = PASSAGE) -> DataFrame:
    """docs with the bytes of ``text`` that a repeat of ``size`` bytes covers cut out; other
    columns stay, whatever their names.

    Bytes that are left of a character cut in two are dropped with it. Null text
    stays null; repeated rows are places of their own, so a text that occurs twice and
    is long enough is cut out of both; an empty table gives an empty one.
    """
    keyed, spans = anchors.repeats(docs, rule(size), "suffixes")
    at, names = docs.columns.index("text"), docs.columns
    common.small_batches(docs.sparkSession)
    whole = docs.withColumn("_text_hash_", F.xxhash64("text")).alias("d").join(spans.alias("s"), F.expr("d.doc_id <=> s.doc_id and d._text_hash_ = s.h"), "left")
    rows = whole.select(*[F.col(f"d.`{n}`") for n in names], F.col("s.spans").alias("_spans"))

    def work(batches):
        for b in batches:
            texts = [t.as_py() if (v := s.as_py()) is None or t.as_py() is None else _kept(t.as_py().encode(), v)[0].decode("utf-8", "ignore") for t, s in zip(b.column(at), b.column(len(names)))]
            arrays = [pa.array(texts, pa.string()) if i == at else b.column(i) for i in range(len(names))]
            yield pa.RecordBatch.from_arrays(arrays, names=names)

    return rows.mapInArrow(work, docs.schema)
