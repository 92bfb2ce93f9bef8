"""Repeated stretches of documents: the distributed part that substring and
suffix-array deduplication share.

A document is a sequence of symbols (words or bytes). A window is ``size``
consecutive symbols. Of the ``prefix``-symbol grams in a window the one (or the
equal ones) with the smallest hash are its anchors, so equal windows hold equal
anchors at equal places, and only about 2 / (size - prefix + 2) of all positions
are anchors: a sparse set of suffixes that misses no repeat.

1. Anchors are grouped by the hash of their gram. Those whose whole surroundings
   (every window that holds the anchor) are equal, by two independent 64-bit
   hashes, form a class and are decided at once. Equal classes of a batch are
   merged before the shuffle.
2. Where a gram has several classes, one member of each class fetches its text.
   The suffixes behind the anchor and the reversed text before it are ordered by
   the operator's own method; from the orders and their common-prefix lengths
   follows which windows two classes share.
3. Covered spans are merged per document and cut out of the text.

A rule may ask for a second, ``shorter`` length. Anchors are then those of the shorter
windows, surroundings reach as far as the longer ones, and the same orders and classes give
the spans of both lengths.

A gram that is frequent (a passage in a third of all rows) is dealt by surroundings instead
of by gram in step 1, where a sample shows it. A gram that has over ``GROUP`` classes, by an
exact count, gets longer prefixes in step 2: its windows are compared whole, as grams of
full length, with equal ones merged before the shuffle, so that the groups of step 2
are bounded. Both only move work; every anchor is decided either way, by the same rule.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

#: Symbols hashed at a time; long texts go through in overlapping blocks.
BLOCK = 1 << 18
#: Documents looked at for frequent grams, as one in so many; a gram is frequent from so many
#: sightings and from this share of an average partition's anchors.
SAMPLE_ONE_IN, SIGHTINGS, PARTITION_SHARE = 64, 24, 0.5
#: Frequent grams of the sample that are sent to every task at most (8 bytes each).
FREQUENT = 20_000
#: Classes of one gram that are compared in one task; a gram with more goes by its windows.
GROUP = 100_000

ANCHOR, SPAN, REPRESENTATIVE, FREQUENT_ONE, SHORT_SPAN = 0, 1, 2, 3, 4
_ROW = pa.schema([("p", pa.int64()), ("g", pa.int64()), ("c", pa.int64()), ("doc_id", pa.int64()), ("h", pa.int64()), ("pos", pa.int64()), ("n", pa.int64()), ("kind", pa.int8()), ("seen", pa.bool_())])
ROW = "p long, g long, c long, doc_id long, h long, pos long, n long, kind byte, seen boolean"
_U = np.uint64


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ x >> _U(30)) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ x >> _U(27)) * _U(0x94D049BB133111EB)
    return x ^ x >> _U(31)


_BASES = (_U(0x9E3779B97F4A7C15), _U(0xD1342543DE82EF95))
_power_tables: list[tuple[np.ndarray, np.ndarray]] = []


def _powers() -> list[tuple[np.ndarray, np.ndarray]]:
    """Powers of both bases and of their inverses modulo 2**64."""
    if not _power_tables:
        for base in _BASES:
            n = BLOCK + 4096
            inverse = _U(pow(int(base), -1, 1 << 64))
            up, down = np.full(n, base, _U), np.full(n, inverse, _U)
            up[0] = down[0] = 1
            _power_tables.append((np.cumprod(up, dtype=_U), np.cumprod(down, dtype=_U)))
    return _power_tables


def sums(symbols: np.ndarray, base: int) -> np.ndarray:
    """Prefix sums from which :func:`hashed` takes the hash of any stretch."""
    out = np.zeros(len(symbols) + 1, _U)
    np.cumsum(symbols * _powers()[base][0][: len(symbols)], out=out[1:])
    return out


def hashed(prefix: np.ndarray, base: int, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    return mix((prefix[end] - prefix[start]) * _powers()[base][1][start])


def _sliding(x: np.ndarray, w: int, f, pad) -> np.ndarray:
    """f over every w neighbours, in three passes."""
    n = len(x) - w + 1
    if w == 1:
        return x
    full = np.concatenate([x, np.full(-len(x) % w, pad, x.dtype)]).reshape(-1, w)
    left = f.accumulate(full, axis=1).ravel()
    right = f.accumulate(full[:, ::-1], axis=1)[:, ::-1].ravel()
    return f(right[:n], left[w - 1 : w - 1 + n])


@dataclass(frozen=True)
class Rule:
    """What a repeat is, and how symbols are made and ordered."""

    size: int
    prefix: int
    #: UTF-8 text -> 64-bit hashes of its symbols.
    symbols: Callable[[bytes], np.ndarray]
    #: UTF-8 text -> something that ``cut`` slices.
    split: Callable[[bytes], object]
    #: (split text, start, end) -> bytes of the symbols, and back into sortable symbols.
    cut: Callable[[object, int, int], bytes]
    back: Callable[[bytes], object]
    #: sequences -> their order, with ``depths`` (common-prefix lengths at which their classes may
    #: change), ``classes(depth)`` (a number for each; equal ones share ``depth`` symbols) and
    #: ``between()`` (the common prefix of each two, for few).
    order: Callable[[list], object]
    #: Length of the longest common prefix of two sequences.
    prefix_of: Callable[[object, object], int]
    #: Only a smaller doc_id counts as an earlier occurrence; else any other place does.
    earlier: bool = field(default=False)
    #: A second, shorter length whose spans are reported beside; 0: none.
    shorter: int = field(default=0)

    @property
    def reach(self) -> int:
        return self.size - self.prefix

    @property
    def least(self) -> int:
        """Length of the windows whose anchors are taken."""
        return self.shorter or self.size

    @property
    def kinds(self) -> list[tuple[int, int]]:
        """(length, kind of its spans) of every length asked for."""
        return [(self.size, SPAN)] + ([(self.shorter, SHORT_SPAN)] if self.shorter else [])


def anchors(symbols: np.ndarray, rule: Rule) -> tuple[np.ndarray, ...]:
    """Position, gram hash, hash of the surroundings, and their reach to the left
    and to the right, of every anchor of a document."""
    n, w = len(symbols), rule.least - rule.prefix + 1
    found: list = [[np.empty(0, t)] for t in (np.int64, _U, _U, np.int64, np.int64)]
    at = 0
    while n - at >= rule.least or (at and at < n):
        # The windows around the anchors in [at, at + BLOCK) reach so far.
        lo, hi = max(0, at - rule.size), min(n, at + BLOCK + 2 * rule.size)
        part, last = symbols[lo:hi], at + BLOCK >= n
        grams_of = sums(part, 0)
        ends = np.arange(rule.prefix, len(part) + 1)
        grams = hashed(grams_of, 0, ends - rule.prefix, ends)
        least = _sliding(grams, w, np.minimum, _U(2**64 - 1))
        padded = np.concatenate([np.zeros(w - 1, _U), least, np.zeros(w - 1, _U)])
        pos = np.flatnonzero(_sliding(padded, w, np.maximum, _U(0)) == grams)
        pos = pos[(pos + lo >= at) & ((pos + lo < at + BLOCK) | last)]
        left, right = np.minimum(pos + lo, rule.reach), np.minimum(n - lo - pos, rule.size)
        left = np.minimum(left, pos)
        around = hashed(sums(part, 1), 1, pos - left, pos + right) ^ mix((left * 4096 + right).astype(_U))
        for have, new in zip(found, (pos + lo, grams[pos], around, left, right)):
            have.append(new)
        if last:
            break
        at += BLOCK
    return tuple(np.concatenate(x) for x in found)


def windows(symbols: np.ndarray, rule: Rule, pos: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, hash, second hash) of every window of ``size`` that holds an anchor at one of pos."""
    n = len(symbols)
    starts = np.unique((pos[:, None] - np.arange(size - rule.prefix + 1)[None, :]).ravel()) if len(pos) else np.empty(0, np.int64)
    starts = starts[(starts >= 0) & (starts + size <= n)]
    out: list = [[], []]
    for lo in range(0, n, BLOCK):
        own = starts[(starts >= lo) & (starts < lo + BLOCK)] - lo
        if len(own):
            part = symbols[lo : lo + BLOCK + size]
            for i in (0, 1):
                out[i].append(hashed(sums(part, i), i, own, own + size))
    return starts, *(np.concatenate(x) if x else np.empty(0, _U) for x in out)


class Sorted:
    """Sequences in order, and the common prefix of each with the one before."""

    def __init__(self, order: list[int], lcp: list[int]):
        self.order, self.lcp = np.array(order, np.int64), np.array(lcp, np.int64)
        self.lcp[:1] = -1
        self.depths = np.unique(self.lcp[1:])

    def classes(self, depth: int) -> np.ndarray:
        out = np.empty(len(self.order), np.int64)
        out[self.order] = np.cumsum(self.lcp < depth)
        return out

    def between(self) -> np.ndarray:
        """Common prefix of each two: the least one between them in the order."""
        n = len(self.order)
        out = np.zeros((n, n), np.int64)
        for a in range(n - 1):
            at, after = self.order[a], self.order[a + 1 :]
            out[at, after] = out[after, at] = np.minimum.accumulate(self.lcp[a + 1 :])
        return out


def merged(starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Union of spans, as disjoint spans in order."""
    if not len(starts):
        return starts, ends
    order = np.argsort(starts, kind="stable")
    starts, ends = starts[order], np.maximum.accumulate(ends[order])
    new = np.concatenate([[True], starts[1:] > ends[:-1]])
    return starts[new], ends[np.concatenate([np.flatnonzero(new)[1:] - 1, [len(starts) - 1]])]


_NO_ID = (1 << 63) - 1
#: Added to the kind of its spans, the kind of a whole window.
_WHOLE = 8
_COLUMNS = ("p", "g", "c", "doc", "h", "pos", "n", "kind", "seen")


def decided(t: dict, rule: Rule) -> tuple[np.ndarray, np.ndarray]:
    """Of rows sorted by (g, c, doc): which are covered by their class and were not before, which stand for it.

    Sets ``seen`` where a class has a second place; the spans of such rows are known.
    """
    g, c, doc = t["g"], t["c"], t["doc"]
    same = np.concatenate([[False], (g[1:] == g[:-1]) & (c[1:] == c[:-1])])
    first = np.maximum.accumulate(np.where(same, 0, np.arange(len(g))))
    if rule.earlier:
        covered = (doc > doc[first]) & (doc != _NO_ID)
        return covered, ~covered
    n = np.bincount(first, minlength=len(g)) + np.bincount(first, weights=t["seen"], minlength=len(g)).astype(np.int64)
    before, t["seen"] = t["seen"].astype(bool), n[first] > 1
    return t["seen"] & ~before, ~same


def _take(t: dict, at) -> dict:
    return {k: v[at] for k, v in t.items()}


def _rows(t: dict):
    """A table of rows as Arrow batches."""
    for i in range(0, len(t["g"]), 50_000):
        x = _take(t, slice(i, i + 50_000))
        ids = pa.array(x["doc"], pa.int64(), mask=x["doc"] == _NO_ID)
        yield common.batch(_ROW, x["p"].view(np.int64), x["g"].view(np.int64), x["c"].view(np.int64), ids, x["h"].astype(np.int64), x["pos"], x["n"], x["kind"].astype(np.int8), x["seen"].astype(bool))


def _table(b) -> dict:
    x = {k: b.column(i).to_numpy(zero_copy_only=False) for i, k in enumerate(_COLUMNS) if k != "doc"}
    x["doc"] = b.column(3).fill_null(_NO_ID).to_numpy()
    x["g"], x["c"], x["p"] = x["g"].view(_U), x["c"].view(_U), x["p"].view(_U)
    return x


def _spans(doc, h, starts, ends, kind: int = SPAN) -> dict:
    """Rows of covered spans, merged per document."""
    order = np.lexsort((ends, starts, h, doc))
    doc, h, starts, ends = (x[order] for x in (doc, h, starts, ends))
    new_doc = np.concatenate([[True], (doc[1:] != doc[:-1]) | (h[1:] != h[:-1])]) if len(doc) else np.empty(0, bool)
    # Spans of different documents are kept apart by an offset that only grows.
    turn = np.cumsum(new_doc)
    lift = turn * (int(ends.max(initial=0)) + 2)
    top = np.maximum.accumulate(ends + lift)
    new = np.concatenate([[True], (starts + lift)[1:] > top[:-1]]) if len(doc) else new_doc
    at = np.flatnonzero(new)
    stop = (top - lift)[np.concatenate([at[1:] - 1, [len(doc) - 1]])] if len(at) else top
    z = np.zeros(len(at), _U)
    p = mix(starts[at].astype(_U) ^ mix(doc[at].astype(_U)))
    return {"p": p, "g": z, "c": z, "doc": doc[at], "h": h[at], "pos": starts[at], "n": stop - starts[at], "kind": np.full(len(at), kind), "seen": z.astype(bool)}


def _own_spans(t: dict, at: np.ndarray, rule: Rule):
    """Rows of the spans around covered anchors, for each length."""
    x = _take(t, at)
    left, right = x["n"] >> 32, x["n"] & 0xFFFFFFFF
    for size, kind in rule.kinds:
        a, b = np.minimum(left, size - rule.prefix), np.minimum(right, size)
        fits = a + b >= size
        yield from _rows(_spans(x["doc"][fits], x["h"][fits].astype(np.int64), (x["pos"] - a)[fits], (x["pos"] + b)[fits], kind))


def _sorted(t: dict) -> dict:
    return _take(t, np.lexsort((t["pos"], t["doc"], t["c"], t["g"])))


def _first_pass(rule: Rule, frequent):
    """Documents to anchors, merged within the batch, and spans that the batch decides."""

    def work(batches):
        hot = np.array(frequent.value, np.int64).view(_U)
        for b in batches:
            texts, size = b.column(1).fill_null(""), 0
            ids, hashes = b.column(0).fill_null(_NO_ID).to_numpy(), b.column(2).to_numpy()
            for lo, hi in _portions(texts):
                made = [anchors(rule.symbols(texts[i].as_py().encode()), rule) for i in range(lo, hi)]
                sizes = np.array([len(x[0]) for x in made])
                if not sizes.sum():
                    continue
                pos, g, c, left, right = (np.concatenate([x[i] for x in made]) for i in range(5))
                row = np.repeat(np.arange(lo, hi), sizes)
                is_hot = np.isin(g, hot)
                t = _sorted({"p": np.where(is_hot, mix(g ^ c), g), "g": g, "c": c, "doc": ids[row], "h": hashes[row], "pos": pos, "n": left << 32 | right, "kind": np.where(is_hot, FREQUENT_ONE, ANCHOR), "seen": np.zeros(len(g), bool)})
                covered, kept = decided(t, rule)
                yield from _own_spans(t, covered, rule)
                yield from _rows(_take(t, kept))

    return work


def _portions(texts, most: int = 1 << 22):
    """Stretches of a batch of about ``most`` bytes, a longer text alone."""
    import pyarrow.compute as pc

    sizes, lo, total = pc.binary_length(texts).to_pylist(), 0, 0
    for i, n in enumerate(sizes):
        if total and total + n > most:
            yield lo, i
            lo, total = i, 0
        total += n
    if lo < len(sizes):
        yield lo, len(sizes)


def _sorted_groups(batches, most: int = 200_000, shrink=None):
    """Tables of whole gram groups out of batches sorted by (p, g, c, doc); spans alone.

    A group of more than ``most`` rows is shrunk to what stands for its classes.
    """
    rest = None
    for b in batches:
        t = _table(b)
        passed = (t["kind"] == SPAN) | (t["kind"] == SHORT_SPAN)
        if passed.any():
            yield None, _rows(_take(t, passed))
            t = _take(t, ~passed)
        if not len(t["g"]):
            continue
        if rest is not None:
            t = {k: np.concatenate([rest[k], t[k]]) for k in t}
        last = int(np.flatnonzero(np.concatenate([[True], t["p"][1:] != t["p"][:-1]]))[-1])
        rest = _take(t, slice(last, None))
        if last:
            yield _take(t, slice(0, last)), None
        if len(rest["g"]) > most:
            spans, rest = shrink(_sorted(rest))
            yield None, spans
    if rest is not None:
        yield rest, None


def _whole_spans(t: dict, at: np.ndarray, rule: Rule):
    """Rows of covered whole windows; the kind of a window tells its length."""
    x = _take(t, at)
    for _, kind in rule.kinds:
        own = x["kind"] == kind + _WHOLE
        yield from _rows(_spans(x["doc"][own], x["h"][own].astype(np.int64), x["pos"][own], x["pos"][own] + x["n"][own], kind))


def _classes(rule: Rule, whole: bool):
    """Sorted anchors to spans of covered ones and representatives of grams with several classes.

    ``whole``: the rows are whole windows, so a class decides them and nothing else is left.
    """
    spans_of = _whole_spans if whole else _own_spans

    def shrink(t):
        covered, kept = decided(t, rule)
        return list(spans_of(t, covered, rule)), _take(t, kept)

    def work(batches):
        for t, passed in _sorted_groups(batches, shrink=shrink):
            if passed is not None:
                yield from passed
                continue
            t = _sorted(t)
            covered, kept = decided(t, rule)
            yield from spans_of(t, covered, rule)
            if whole:
                continue
            g, c = t["g"], t["c"]
            new_g = np.concatenate([[True], g[1:] != g[:-1]])
            new_c = new_g | np.concatenate([[True], c[1:] != c[:-1]])
            group = np.cumsum(new_g) - 1
            several = np.bincount(group, weights=new_c)[group] > 1
            out = _take(t, kept & (several | (t["kind"] == FREQUENT_ONE)))
            out["kind"] = np.where(out["kind"] == FREQUENT_ONE, FREQUENT_ONE, REPRESENTATIVE)
            yield from _rows(out)

    return work


_TEXT = pa.schema([("g", pa.int64()), ("doc_id", pa.int64()), ("h", pa.int64()), ("left", pa.int32()), ("pos", pa.list_(pa.int64())), ("around", pa.binary())])
TEXT = "g long, doc_id long, h long, left int, pos array<long>, around binary"


def _surroundings(rule: Rule):
    """(doc_id, h, text, anchors) to the text around each anchor; equal ones of a document once."""

    def work(batches):
        for b in batches:
            rows = []
            for doc, text, h, have in zip(*(b.column(i) for i in range(4))):
                parts, by = rule.split((text.as_py() or "").encode()), {}
                for a in have.as_py():
                    left, right = a["n"] >> 32, a["n"] & 0xFFFFFFFF
                    by.setdefault((a["g"], left, rule.cut(parts, a["pos"] - left, a["pos"] + right)), []).append(a["pos"])
                rows += [(g, doc.as_py(), h.as_py(), left, pos, around) for (g, left, around), pos in by.items()]
                if len(rows) > 2000:
                    yield common.batch(_TEXT, *zip(*rows))
                    rows = []
            if rows:
                yield common.batch(_TEXT, *zip(*rows))

    return work


def _outermost(rule: Rule, reach: int, docs: np.ndarray, right, left) -> tuple[np.ndarray, np.ndarray]:
    """Least and greatest offset of the windows of ``reach`` beyond the gram that each member
    shares, from the orders of both sides."""
    k = len(docs)
    low, high = np.full(k, reach + 1), np.full(k, -1)
    offsets = np.unique(np.concatenate([np.minimum(left.depths, reach), np.maximum(reach - right.depths, 0)]))
    for o in offsets[(offsets >= 0) & (offsets <= reach)].tolist():
        _, of, n = np.unique(right.classes(reach - o) * (k + 1) + left.classes(o), return_inverse=True, return_counts=True)
        if rule.earlier:
            least = np.full(len(n), _NO_ID)
            np.minimum.at(least, of, docs)
            hit = (docs > least[of]) & (docs != _NO_ID)
        else:
            hit = n[of] > 1
        low[hit & (low > reach)] = o
        high[hit] = o
    return low, high


#: Members up to which the common prefixes of each two are laid out.
FEW = 32


def _outermost_of_few(rule: Rule, reach: int, docs: np.ndarray, ahead: np.ndarray, behind: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The same for few members, from the common prefixes of each two on both sides."""
    lo, hi = np.maximum(0, reach - ahead), np.minimum(reach, behind)
    ok = lo <= hi
    np.fill_diagonal(ok, False)
    if rule.earlier:
        ok &= (docs[None, :] < docs[:, None]) & (docs != _NO_ID)[:, None]
    return np.where(ok, lo, reach + 1).min(axis=1), np.where(ok, hi, -1).max(axis=1)


def shared(rule: Rule, left: list, right: list, docs: np.ndarray):
    """For each length (in the order of ``rule.kinds``): least and greatest offset of the windows
    that each member of a group shares; the least is over the reach where there is none.

    A window at offset o needs o symbols before the anchor and reach - o behind its
    gram. Two members share it if they fall in one class of the left order at depth o
    and in one class of the right order at depth reach - o. The classes change only
    at the common-prefix lengths, so only offsets that these lengths set are looked at.
    All windows of an anchor overlap, so the outermost two bound what is covered.
    """
    ahead, behind = rule.order(right), rule.order(left)
    if len(docs) <= FEW:
        ahead, behind = ahead.between(), behind.between()
        return [_outermost_of_few(rule, size - rule.prefix, docs, ahead, behind) for size, _ in rule.kinds]
    return [_outermost(rule, size - rule.prefix, docs, ahead, behind) for size, _ in rule.kinds]


def _compared(rule: Rule):
    """Surroundings sorted by gram to the spans that different classes share."""

    def found(rows) -> None:
        if len(rows) < 2:
            return
        left = [rule.back(r[5])[: r[3]][::-1] for r in rows]
        right = [rule.back(r[5])[r[3] + rule.prefix :] for r in rows]
        if len(rows) == 2:
            # A tree of two has one inner node: the common prefix.
            ahead, behind, docs = rule.prefix_of(*right), rule.prefix_of(*left), (rows[0][1], rows[1][1])
            for size, kind in rule.kinds:
                reach = size - rule.prefix
                lo, hi = max(0, reach - ahead), min(reach, behind)
                for i in (0, 1) if lo <= hi else ():
                    if not rule.earlier or docs[i] is not None and docs[1 - i] is not None and docs[1 - i] < docs[i]:
                        doc = _NO_ID if docs[i] is None else docs[i]
                        spans.setdefault(kind, []).extend((doc, rows[i][2], p - hi, p - lo + size) for p in rows[i][4])
            return
        docs = np.array([_NO_ID if r[1] is None else r[1] for r in rows], np.int64)
        for (size, kind), (low, high) in zip(rule.kinds, shared(rule, left, right, docs)):
            spans.setdefault(kind, []).extend((docs[i], rows[i][2], p - high[i], p - low[i] + size) for i in np.flatnonzero(high >= 0).tolist() for p in rows[i][4])

    spans: dict[int, list] = {}

    def flush(least):
        for kind, have in spans.items():
            if len(have) > least:
                yield from _rows(_spans(*(np.array(x, np.int64) for x in zip(*have)), kind))
                have.clear()

    def work(batches):
        group: list = []
        for b in batches:
            for r in zip(*(b.column(i).to_pylist() for i in range(6))):
                if group and group[0][0] != r[0]:
                    found(group)
                    group = []
                group.append(r)
            yield from flush(20_000)
        found(group)
        yield from flush(0)

    return work


def _whole_windows(rule: Rule):
    """(doc_id, h, text, frequent anchors) to their windows as grams of full length."""

    def work(batches):
        for b in batches:
            for doc, text, h, have in zip(*(b.column(i) for i in range(4))):
                pos = np.array([a["pos"] for a in have.as_py()], np.int64)
                doc_id, symbols = _NO_ID if doc.as_py() is None else doc.as_py(), rule.symbols((text.as_py() or "").encode())
                for size, kind in rule.kinds:
                    start, g, c = windows(symbols, rule, pos, size)
                    if not len(start):
                        continue
                    z = np.zeros(len(start), np.int64)
                    t = _sorted({"p": g, "g": g, "c": c, "doc": z + doc_id, "h": z + h.as_py(), "pos": start, "n": z + size, "kind": z + kind + _WHOLE, "seen": z.astype(bool)})
                    covered, kept = decided(t, rule)
                    yield from _whole_spans(t, covered, rule)
                    yield from _rows(_take(t, kept))

    return work


def repeats(docs: DataFrame, rule: Rule, name: str) -> tuple[DataFrame, DataFrame]:
    """(documents with the hash of their text, covered spans) of a table of documents.

    Documents: doc_id, text, h. Spans: doc_id, h, spans (array of pos, n and kind, which
    may overlap), one row per document with any.
    """
    spark = docs.sparkSession
    stage, n = common.Stage(spark, name), common.partitions(spark)
    common.small_batches(spark)
    keyed = common.columns(docs, ["doc_id", "text"]).withColumn("h", F.xxhash64("text"))

    def seen(batches):
        schema = pa.schema([("g", pa.int64())])
        for b in batches:
            for t in b.column(1).fill_null(""):
                # Once a class of a document: equal ones of a document are merged before the shuffle anyway.
                _, g, c, *_ = anchors(rule.symbols(t.as_py().encode()), rule)
                yield common.batch(schema, g[np.unique(mix(g ^ mix(c)), return_index=True)[1]].view(np.int64))

    sighted = keyed.sample(1 / SAMPLE_ONE_IN, 7).mapInArrow(seen, "g long").groupBy("g").count()
    sighted = stage.save(sighted, "sighted")
    total = sighted.agg(F.sum("count")).first()[0] or 0
    common_grams = sighted.filter(F.col("count") >= max(SIGHTINGS, PARTITION_SHARE * total / n))
    frequent = spark.sparkContext.broadcast([r.g for r in common_grams.orderBy(F.desc("count"), "g").limit(FREQUENT).collect()])

    dealt = keyed.mapInArrow(_first_pass(rule, frequent), ROW).repartition(n, "p").sortWithinPartitions("p", "g", "c", "doc_id")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "50000")
    first = stage.save(dealt.mapInArrow(_classes(rule, False), ROW), "first")
    common.small_batches(spark)
    stage.release()

    stand = first.filter(F.col("kind").isin(REPRESENTATIVE, FREQUENT_ONE))
    heavy = stage.save(stand.groupBy("g").count().filter(F.col("count") > GROUP).select("g"), "heavy")
    whole_ones, some_heavy = None, bool(heavy.limit(1).count())
    if some_heavy:
        stand, whole_ones = stand.join(heavy, "g", "left_anti"), stand.join(heavy, "g", "left_semi")

    def with_text(rows: DataFrame) -> DataFrame:
        of = rows.groupBy("doc_id", "h").agg(F.collect_list(F.struct("g", "pos", "n")).alias("have"))
        return keyed.alias("d").join(of.alias("o"), F.expr("d.doc_id <=> o.doc_id and d.h = o.h")).select("d.doc_id", "d.text", "d.h", "o.have")

    around = with_text(stand).mapInArrow(_surroundings(rule), TEXT)
    second = stage.save(around.repartition(n, "g").sortWithinPartitions("g").mapInArrow(_compared(rule), ROW), "second")
    stage.release()
    columns = ["doc_id", "h", "pos", "n", "kind"]
    spans = first.filter(F.col("kind").isin(SPAN, SHORT_SPAN)).select(*columns).unionByName(second.select(*columns))
    if some_heavy:
        whole = with_text(whole_ones).mapInArrow(_whole_windows(rule), ROW).repartition(n, "p").sortWithinPartitions("p", "g", "c", "doc_id")
        third = stage.save(whole.mapInArrow(_classes(rule, True), ROW), "third")
        stage.release()
        spans = spans.unionByName(third.select(*columns))
    return keyed, spans.groupBy("doc_id", "h").agg(F.collect_list(F.struct("pos", "n", "kind")).alias("spans"))


def with_spans(docs: DataFrame, spans: DataFrame) -> DataFrame:
    """(doc_id, text, spans) of every row of docs; spans are null where nothing repeats."""
    common.small_batches(docs.sparkSession)
    return docs.alias("d").join(spans.alias("s"), F.expr("d.doc_id <=> s.doc_id and d.h = s.h"), "left").select("d.doc_id", "d.text", "s.spans")


def union(spans: list | None, kind: int = SPAN) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the disjoint, maximal runs that spans of a kind cover."""
    own = [s for s in spans or () if s["kind"] == kind]
    starts = np.array([s["pos"] for s in own], np.int64)
    return merged(starts, starts + np.array([s["n"] for s in own], np.int64))
