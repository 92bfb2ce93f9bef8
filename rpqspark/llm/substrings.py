"""Substring deduplication over words, by prefix-partitioned suffix trees.

Suffixes are grouped by a prefix of ``prefix`` words; frequent prefixes are
lengthened, so that every group fits in memory (see ``anchors``). The suffixes of a group
are put into a tree of their own (:class:`Subtree`): edges carry words, a node's depth
is the number of words down to it, and every inner node is a maximal repeat of the
suffixes below it. Inner nodes deep enough, together with those of the tree of the
text before the prefix, give the repeated windows.

A word is removed if a window of ``size`` words of this document covers it whose
word sequence also starts in a document with a smaller doc_id. Documents without
an id neither cover others nor lose words; null text has no words; rows with one
doc_id are one document's and do not cover each other; an empty table gives an empty one.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame

from . import anchors, common
from .bpe import Finished

SIZE, PREFIX = 13, 5
_hashes = Finished(lambda w: xxhash.xxh64_intdigest(w, 1), most=100_000)


def word_hashes(text: bytes) -> np.ndarray:
    words = text.split()
    return np.fromiter(map(_hashes.__getitem__, words), np.uint64, len(words))


class Node:
    """A node of a suffix tree: its depth in words, children by the next word, suffixes that end here."""

    __slots__ = ("depth", "children", "ends")

    def __init__(self, depth: int):
        self.depth, self.children, self.ends = depth, {}, []


class Subtree(anchors.Sorted):
    """The suffix tree of the suffixes of one prefix group.

    An edge is named by its first word and holds (node below, suffix that spells it); the
    words between two depths are read from that suffix. The leaves in the order of a walk,
    each with the depth of the inner node that joins it with the one before, say which suffixes
    lie below a node of some depth. ``repeats`` lists the inner nodes themselves.
    """

    def __init__(self, suffixes: list[list[bytes]]):
        self.suffixes, self.root = suffixes, Node(0)
        for i, s in enumerate(suffixes):
            self._add(i, s)
        super().__init__(*self._walk())

    @property
    def repeats(self) -> list[tuple[int, list[int]]]:
        """Depth and suffixes, two or more, of every inner node, children before parents."""
        return [(node.depth, below) for node, below in self._below() if len(below) > 1]

    def _walk(self) -> tuple[list[int], list[int]]:
        order, joined, stack = [], [], [(self.root, -1)]
        while stack:
            node, by = stack.pop()
            for i in node.ends:
                order.append(i)
                joined.append(by)
                by = node.depth
            children = [child for child, _ in node.children.values()]
            stack += [(child, node.depth) for child in children[:0:-1]]
            stack += [(child, by) for child in children[:1]]
        return order, joined

    def _add(self, i: int, s: list[bytes]) -> None:
        node, at = self.root, 0
        while at < len(s):
            edge = node.children.get(s[at])
            if edge is None:
                leaf = Node(len(s))
                node.children[s[at]] = (leaf, i)
                node, at = leaf, len(s)
                break
            below, speller = edge
            spelled, end = self.suffixes[speller], min(below.depth, len(s))
            while at < end and spelled[at] == s[at]:
                at += 1
            if at < below.depth:
                # The edge is split where the suffix leaves it.
                middle = Node(at)
                middle.children[spelled[at]] = (below, speller)
                node.children[spelled[node.depth]] = (middle, speller)
                below = middle
            node = below
        node.ends.append(i)

    def _below(self) -> list[tuple[Node, list[int]]]:
        """Every node with all suffixes that pass it, children before parents."""
        out, found, stack = [], {}, [(self.root, False)]
        while stack:
            node, done = stack.pop()
            if not done:
                stack.append((node, True))
                stack += [(child, False) for child, _ in node.children.values()]
                continue
            below = list(node.ends)
            for child, _ in node.children.values():
                below += found.pop(id(child))
            found[id(node)] = below
            out.append((node, below))
        return out


def _same_words(a: list[bytes], b: list[bytes]) -> int:
    n = min(len(a), len(b))
    return next((k for k in range(n) if a[k] != b[k]), n)


RULE = anchors.Rule(SIZE, PREFIX, word_hashes, bytes.split, lambda w, s, e: b" ".join(w[s:e]), lambda x: x.split(b" "), Subtree, _same_words, earlier=True)


def repeated_words(docs: DataFrame, digest: bool = False) -> DataFrame:
    """One row per document: doc_id, n_words, n_removed, and the kept text (its
    words joined by one space) or, with ``digest``, its SHA-256."""
    keyed, spans = anchors.repeats(docs, RULE, "substrings")
    name = "kept_sha256" if digest else "text"
    schema = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), (name, pa.string())])

    def work(batches):
        for b in batches:
            rows = []
            for text, spans in zip(b.column(1), b.column(2)):
                words, at, kept = (text.as_py() or "").encode().split(), 0, []
                for s, e in zip(*(x.tolist() for x in anchors.union(spans.as_py()))):
                    kept += words[at:s]
                    at = e
                kept += words[at:]
                out = b" ".join(kept)
                rows.append((len(words), len(words) - len(kept), hashlib.sha256(out).hexdigest() if digest else out.decode()))
            yield common.batch(schema, b.column(0), *zip(*rows)) if rows else common.batch(schema, [], [], [], [])

    return anchors.with_spans(keyed, spans).mapInArrow(work, f"doc_id long, n_words long, n_removed long, {name} string")
