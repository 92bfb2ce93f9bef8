"""Quality classifier by co-training of a text view and a metadata view.

Text view: presence of words and of word beginnings, hashed, and measures of repetition,
capitals, symbols and layout. Metadata view: language, source and size. Both views
carry two heads, one for low quality and one for toxic text. A head is a
logistic regression. It is first fitted on labelled rows; in each round, each view
then labels those unlabelled rows of which it is confident, and the other view learns
from them too. Each view's log-odds are calibrated on labelled rows kept out of the
fit, and the views are combined by adding calibrated log-odds over the base rate. A
document is rejected if either head finds it more likely bad than not.

Labelled rows of the fit are a sample, chosen by a hash of doc_id: ``LABELLED`` at most, and
only their hashed features reach the driver. Every other document is unlabelled and takes
part in each round: features are stored once, executors label what a view is confident of
and add up what the other view's fit needs (sums per feature, then loss and gradient of the
regression at ``PASSES`` points). Where lent rows outnumber labelled ones, all of them
together weigh as much as the labelled rows. Every document is
scored over its whole text. Null text is scored like empty text; unknown languages and
sources count as seen in no fit; labels that are null are left out for
their head; a head whose labels are all alike rejects nothing. Repeated rows are scored alike.
"""

from __future__ import annotations

import math
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common
from .anchors import mix

LABELLED, ROUNDS, CONFIDENT, PASSES = 8000, 3, 0.98, 8
WORD_BITS, META_BITS, BEGINNING = 18, 12, 4
#: Chi-square from which a hashed feature takes part in a fit.
TELLING = 12.0
HEADS = ("low quality", "toxic")
_MARKS = "!#$%&*|<>=_~^@\\{}[]"
_STRIP = ".,;:?\"'()«»¿¡-" + _MARKS


def _slot(text: str, bits: int) -> int:
    return zlib.crc32(text.encode()) & (1 << bits) - 1


# Classes of bytes: white space between words, and what is stripped from a word's ends (the last
# four stand in the two-byte marks of quotation and of opening questions and exclamations).
_SPACE, _BARE = np.zeros(256, bool), np.ones(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_BARE[np.flatnonzero(_SPACE)] = False
_BARE[list(_STRIP.encode())] = False
#: Random numbers for each byte and, taken modulo their number, each place in a word.
_OF_BYTE, _OF_PLACE = (np.random.default_rng(n).integers(1, 1 << 63, 256, dtype=np.uint64) | np.uint64(1) for n in (5, 6))
#: Bytes of text whose features are made at once; a longer text is taken alone.
_PORTION = 1 << 20


def _hash_words(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the stretches of bytes, and of the first ``BEGINNING`` characters of each."""
    sizes = ends - starts
    before = np.cumsum(sizes) - sizes
    place = np.arange(int(sizes.sum())) - np.repeat(before, sizes)
    of = data[np.repeat(starts, sizes) + place]
    terms = _OF_BYTE[of] * _OF_PLACE[place & 255]
    characters = np.cumsum((of & 0xC0) != 0x80)
    first = characters - np.repeat(characters[before] - 1, sizes) <= BEGINNING
    return mix(np.add.reduceat(terms, before)), mix(np.add.reduceat(np.where(first, terms, 0), before) ^ np.uint64(1 << 62))


def _once(keys: np.ndarray) -> np.ndarray:
    """The distinct keys, sorted."""
    keys = np.sort(keys)
    return keys[np.concatenate([[True], keys[1:] != keys[:-1]])] if len(keys) else keys


def _portion_rows(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Slots, their number for each text, and measures."""
    n = len(texts)
    raws = [t.lower().encode() for t in texts]
    firsts = np.cumsum([0] + [len(r) + 1 for r in raws])[:-1]
    data = np.frombuffer(b" ".join([*raws, b""]), np.uint8)
    inside = ~_SPACE[data]
    edge = np.diff(inside.astype(np.int8), prepend=0, append=0)
    starts, ends = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    row = np.searchsorted(firsts, starts, side="right") - 1
    n_words = np.bincount(row, minlength=n)
    keys = [np.empty(0, np.int64)]
    distinct = repeated = np.zeros(n)
    if len(starts):
        whole, _ = _hash_words(data, starts, ends)
        bare = np.flatnonzero(_BARE[data])
        lo, hi = np.searchsorted(bare, starts), np.searchsorted(bare, ends) - 1
        some = hi >= lo
        at = lambda i: bare[np.minimum(i, len(bare) - 1)] if len(bare) else np.zeros_like(i)
        words, beginnings = _hash_words(data, np.where(some, at(lo), starts), np.where(some, at(hi) + 1, ends))
        keys += [row << WORD_BITS | (h & np.uint64((1 << WORD_BITS) - 1)).astype(np.int64) for h in (words, beginnings)]
        again = (whole[1:] == whole[:-1]) & (row[1:] == row[:-1])
        repeated = np.bincount(row[1:], weights=again, minlength=n)
        distinct = np.bincount(_once(row << 40 | (whole >> np.uint64(24)).astype(np.int64)) >> 40, minlength=n)
    keys = _once(np.concatenate(keys))
    dense = []
    for i, text in enumerate(texts):
        words, chars, lines = max(1, int(n_words[i])), max(1, len(text)), text.split("\n")
        dense.append([
            repeated[i] / words,
            distinct[i] / words / (1 + math.log(words)) * 4,
            sum(map(str.isupper, text.split())) / words,
            sum(map(text.count, _MARKS)) / chars * 5,
            text.count("!") / words,
            text.count("|") / words,
            1 - len(set(lines)) / len(lines),
            sum(map(text.count, "0123456789")) / chars,
            math.log(words) / 8,
            chars / words / 20,
            1.0 if words < 8 else 0.0,
        ])
    return keys & (1 << WORD_BITS) - 1, np.bincount(keys >> WORD_BITS, minlength=n), np.array(dense)


def text_rows(texts: list) -> Rows:
    """The text view of texts: hashed word features, sorted in each row, and measures.

    Words are runs of bytes other than ASCII white space, in lower case; marks are stripped from their ends.
    """
    parts, at, size = [], 0, 0
    for i, t in enumerate(texts):
        size += len(t or "")
        if size >= _PORTION or i + 1 == len(texts):
            parts.append(_portion_rows([x or "" for x in texts[at : i + 1]]))
            at, size = i + 1, 0
    if not parts:
        return Rows(np.empty(0, np.int64), np.empty(0, np.int64), np.zeros((0, MEASURES)))
    slots, sizes, dense = (np.concatenate(x) for x in zip(*parts))
    return Rows(slots, np.cumsum(sizes, dtype=np.int64), dense)


MEASURES = 11


def meta_view(lang, source, n_chars) -> list[int]:
    """Hashed metadata features."""
    size = "none" if n_chars is None or n_chars < 0 else str(int(math.log2(n_chars + 1)))
    return [_slot(x, META_BITS) for x in (f"l{lang}", f"s{source}", f"n{size}", f"ls{lang}/{source}")]


@dataclass
class Rows:
    """Sparse rows: slots of row i are slots[ends[i - 1]:ends[i]]; dense measures beside them."""

    slots: np.ndarray
    ends: np.ndarray
    dense: np.ndarray

    @classmethod
    def of(cls, slots: list, dense: list | None = None) -> Rows:
        sizes = [len(s) for s in slots]
        return cls(np.concatenate([np.asarray(s, np.int64) for s in slots]) if slots else np.empty(0, np.int64), np.cumsum(sizes, dtype=np.int64), np.asarray(dense, float) if dense is not None else np.zeros((len(slots), 0)))

    def take(self, at: np.ndarray) -> Rows:
        starts = np.concatenate([[0], self.ends[:-1]])[at]
        sizes = self.ends[at] - starts
        ends = np.cumsum(sizes, dtype=np.int64)
        within = np.arange(int(sizes.sum())) - np.repeat(ends - sizes, sizes)
        return Rows(self.slots[np.repeat(starts, sizes) + within], ends, self.dense[at])

    def sums(self, w: np.ndarray) -> np.ndarray:
        total = np.concatenate([[0.0], np.cumsum(w[self.slots])])
        return total[self.ends] - total[np.concatenate([[0], self.ends[:-1]])]


@dataclass
class Head:
    """Logistic regression over hashed and dense features, with calibration."""

    bits: int
    weights: np.ndarray | None = None
    dense: np.ndarray | None = None
    bias: float = 0.0
    centre: np.ndarray | None = None
    scale: np.ndarray | None = None
    slope: float = 1.0
    shift: float = 0.0

    def fit(self, rows: Rows, y: np.ndarray, steps: int = 200, rate: float = 0.3, keep: float = 2e-5) -> Head:
        n, m = len(y), 1 << self.bits
        self.centre, self.scale = rows.dense.mean(axis=0), rows.dense.std(axis=0) + 1e-6
        x = (rows.dense - self.centre) / self.scale
        self.weights, self.dense = np.zeros(m), np.zeros(x.shape[1])
        self.bias = math.log((y.sum() + 0.5) / (n - y.sum() + 0.5))
        row = np.repeat(np.arange(n), np.diff(np.concatenate([[0], rows.ends])))
        # Only features that tell the classes apart are fitted: a chi-square of 12 or more over three rows or more.
        seen, share = np.bincount(rows.slots, minlength=m), y.mean()
        bad = np.bincount(rows.slots, weights=y[row], minlength=m)
        telling = ((bad - seen * share) ** 2 / (seen * share * (1 - share) + 1e-9) >= TELLING) & (seen >= 3)
        own = telling[rows.slots]
        names, slots = np.unique(rows.slots[own], return_inverse=True)
        row = row[own]
        weights, squares = np.zeros(len(names)), np.full(len(names), 1e-10)
        squares_d, square_b = np.full(x.shape[1], 1e-10), 1e-10
        for _ in range(steps):
            sums = np.bincount(row, weights=weights[slots], minlength=n) if len(names) else 0.0
            z = np.clip(self.bias + sums + x @ self.dense, -30, 30)
            e = (1 / (1 + np.exp(-z)) - y) / n
            gd, gb = x.T @ e + keep * self.dense, e.sum()
            if len(names):
                g = np.bincount(slots, weights=e[row], minlength=len(names)) + keep * weights
                squares += g * g
                weights -= rate * g / np.sqrt(squares)
            squares_d += gd * gd
            square_b += gb * gb
            self.dense -= rate * gd / np.sqrt(squares_d)
            self.bias -= rate * gb / math.sqrt(square_b)
        self.weights[names] = weights
        return self

    def moved(self, names: np.ndarray, centre: np.ndarray, scale: np.ndarray) -> np.ndarray:
        """Weights of ``names``, dense weights and bias as one vector, for another centre and scale."""
        bias = self.bias + float((self.dense * (centre - self.centre) / self.scale).sum())
        return np.concatenate([self.weights[names], self.dense * scale / self.scale, [bias]])

    def odds(self, rows: Rows) -> np.ndarray:
        return self.bias + rows.sums(self.weights) + ((rows.dense - self.centre) / self.scale) @ self.dense

    def calibrate(self, rows: Rows, y: np.ndarray) -> None:
        """Slope and shift by damped Newton steps, the slope pulled towards one."""
        z, a, b = np.clip(self.odds(rows), -15, 15), 1.0, 0.0
        m = np.stack([z, np.ones_like(z)], axis=1)
        for _ in range(50):
            p = 1 / (1 + np.exp(-np.clip(m @ [a, b], -30, 30)))
            g = m.T @ (p - y) + [2 * (a - 1), 0.1 * b]
            h = (m * (p * (1 - p))[:, None]).T @ m + np.diag([2, 0.1])
            step = np.clip(np.linalg.solve(h, g), -0.5, 0.5)
            a, b = a - step[0], b - step[1]
        self.slope, self.shift = max(0.0, float(a)), float(b)

    def calibrated(self, rows: Rows) -> np.ndarray:
        return self.slope * np.clip(self.odds(rows), -15, 15) + self.shift


@dataclass
class Model:
    text: list
    meta: list
    prior: list

    def bad(self, text: Rows, meta: Rows) -> np.ndarray:
        """Probability of each head, one row per head."""
        out = []
        for t, m, base in zip(self.text, self.meta, self.prior):
            if t is None:
                out.append(np.zeros(len(text.ends)))
                continue
            z = t.calibrated(text) + m.calibrated(meta) - base
            out.append(1 / (1 + np.exp(-np.clip(z, -30, 30))))
        return np.array(out)


VIEWS = ("text", "meta")
_BITS = (WORD_BITS, META_BITS)
_CHUNK = 4096
_SUMS = pa.schema([("k", pa.int32()), ("chunk", pa.int32()), ("part", pa.binary())])
#: A gap that only adds to the next one.
_FAR = 65535


def _packed(rows: Rows) -> list[bytes]:
    """Gaps between the sorted slots of each row, two bytes each."""
    starts = np.concatenate([[0], rows.ends])[:-1]
    gaps = np.diff(rows.slots, prepend=0)
    some = starts[rows.ends > starts]
    gaps[some] = rows.slots[some]
    more = gaps // _FAR
    if more.any():
        # A far slot takes marks of its own before the rest of its gap.
        out = np.full(len(gaps) + int(more.sum()), _FAR)
        ends = np.cumsum(more + 1)
        out[ends - 1] = gaps % _FAR
        ends = np.concatenate([[0], ends])[np.concatenate([[0], rows.ends])]
    else:
        out, ends = gaps, np.concatenate([[0], rows.ends])
    data, ends = out.astype("<u2").tobytes(), (2 * ends).tolist()
    return [data[a:b] for a, b in zip(ends, ends[1:])]


def _unpacked(slots: pa.Array, measures: pa.Array, meta: pa.Array) -> tuple[Rows, Rows]:
    n = len(slots)
    gaps = np.frombuffer(b"".join(slots.to_pylist()), "<u2").astype(np.int64)
    sizes = pc.binary_length(slots).to_numpy(zero_copy_only=False).astype(np.int64) // 2
    ends, total, real = np.cumsum(sizes, dtype=np.int64), np.concatenate([[0], np.cumsum(gaps)]), gaps != _FAR
    found = (total[1:] - np.repeat(total[ends - sizes], sizes))[real]
    dense = np.frombuffer(b"".join(measures.to_pylist())).reshape(n, MEASURES)
    named = np.frombuffer(b"".join(meta.to_pylist()), "<u2").astype(np.int64)
    per = len(named) // n if n else 0
    return Rows(found, np.concatenate([[0], np.cumsum(real)])[ends], dense), Rows(named, np.arange(1, n + 1) * per, np.zeros((n, 0)))


def _lent(past: list, rows: tuple[Rows, Rows], confident: float) -> np.ndarray:
    """Labels that heads lend to views, a row for each head and view; NaN where none.

    ``past`` holds each head's pairs of fitted views, one a round; the first confident one counts.
    """
    out = np.full((2 * len(past), len(rows[0].ends)), np.nan)
    for h, pairs in enumerate(past):
        for pair in pairs:
            for v in range(2):
                p = 1 / (1 + np.exp(-pair[1 - v].calibrated(rows[1 - v])))
                own = out[2 * h + v]
                sure = np.isnan(own) & ((p >= confident) | (p <= 1 - confident))
                own[sure] = p[sure] >= 0.5
    return out


def _counts(rows: Rows, y: np.ndarray, m: int) -> np.ndarray:
    """Rows and bad rows of each slot, sums and squares of the dense measures, rows and bad rows."""
    row = np.repeat(np.arange(len(y)), np.diff(np.concatenate([[0], rows.ends])))
    seen = np.bincount(rows.slots, minlength=m)
    bad = np.bincount(rows.slots, weights=y[row], minlength=m)
    return np.concatenate([seen, bad, rows.dense.sum(axis=0), (rows.dense**2).sum(axis=0), [len(y), y.sum()]])


@dataclass
class Point:
    """Weights at which loss and gradient are taken: of ``names``, of the dense measures, and the bias."""

    bits: int
    names: np.ndarray
    centre: np.ndarray
    scale: np.ndarray
    at: np.ndarray

    def slope(self, rows: Rows, y: np.ndarray) -> np.ndarray:
        """Gradient and loss, both summed over rows."""
        n, m = len(y), len(self.names)
        place = np.full(1 << self.bits, -1, np.int32)
        place[self.names] = np.arange(m)
        slots = place[rows.slots]
        own = slots >= 0
        row, slots = np.repeat(np.arange(n), np.diff(np.concatenate([[0], rows.ends])))[own], slots[own]
        x = (rows.dense - self.centre) / self.scale
        z = np.clip(self.at[-1] + np.bincount(row, weights=self.at[slots], minlength=n) + x @ self.at[m:-1], -30, 30)
        e = 1 / (1 + np.exp(-z)) - y
        return np.concatenate([np.bincount(slots, weights=e[row], minlength=m), x.T @ e, [e.sum(), (np.logaddexp(0, z) - y * z).sum()]])


def _summed(rows: DataFrame, widths: dict, made) -> dict:
    """The sums of the vectors that ``made(batch)`` gives as {k: vector}, added up on the executors."""
    spark = rows.sparkSession

    def part(batches):
        total = {k: np.zeros(n) for k, n in widths.items()}
        for b in batches:
            if b.num_rows:
                for k, v in made(b).items():
                    total[k] += v
        for k, v in total.items():
            at = [i for i in range(0, len(v), _CHUNK) if v[i : i + _CHUNK].any()]
            if at:
                yield common.batch(_SUMS, [k] * len(at), [i // _CHUNK for i in at], [v[i : i + _CHUNK].tobytes() for i in at])

    def whole(batches):
        total: dict = {}
        for b in batches:
            for k, chunk, v in zip(*(c.to_pylist() for c in b.columns)):
                total[k, chunk] = total.get((k, chunk), 0.0) + np.frombuffer(v)
        if total:
            yield common.batch(_SUMS, [k for k, _ in total], [c for _, c in total], [v.tobytes() for v in total.values()])

    kind = "k int, chunk int, part binary"
    parts = rows.coalesce(2 * spark.sparkContext.defaultParallelism).mapInArrow(part, kind)
    out = {k: np.zeros(n) for k, n in widths.items()}
    for k, chunk, v in zip(*(c.to_pylist() for c in parts.repartition(common.partitions(spark), "k", "chunk").mapInArrow(whole, kind).toArrow().columns)):
        out[k][chunk * _CHUNK : (chunk + 1) * _CHUNK] = np.frombuffer(v)
    return out


class _Descent:
    """Minimum of a smooth loss by limited-memory quasi-Newton steps, a value and gradient at a time."""

    def __init__(self, start: np.ndarray, curve: np.ndarray):
        self.best = self.next = start
        self.curve, self.pairs, self.loss, self.step = curve, [], math.inf, 1.0

    def told(self, loss: float, g: np.ndarray) -> None:
        """What the loss and gradient are at ``next``; chooses another ``next``."""
        if not loss <= self.loss:
            self.step /= 4
        else:
            if self.loss < math.inf and (s := self.next - self.best) @ (d := g - self.gradient) > 1e-12:
                self.pairs = [*self.pairs[-6:], (s, d)]
            self.best, self.loss, self.gradient, self.step = self.next, loss, g, 1.0
            q, used = g.copy(), []
            for s, d in reversed(self.pairs):
                used.append((s @ q) / (s @ d))
                q -= used[-1] * d
            q /= self.curve
            for (s, d), a in zip(self.pairs, reversed(used)):
                q += (a - (d @ q) / (s @ d)) * s
            self.way = -q
        self.next = self.best + self.step * self.way


class _Labelled:
    """One head's labelled rows: those it is fitted on, and those kept out for calibration."""

    def __init__(self, views: tuple[Rows, Rows], y: np.ndarray):
        held = np.arange(len(y)) % 4 == 3
        fit, check = np.flatnonzero(~held), np.flatnonzero(held)
        if y[check].min() == y[check].max() or y[fit].min() == y[fit].max():
            fit = check = np.arange(len(y))
        self.fit, self.y = [v.take(fit) for v in views], y[fit]
        self.check, self.known = [v.take(check) for v in views], y[check]
        self.prior = math.log((self.known.sum() + 0.5) / (len(check) - self.known.sum() + 0.5))

    def first(self) -> tuple[Head, Head]:
        return tuple(self.calibrated(v, Head(_BITS[v]).fit(self.fit[v], self.y)) for v in range(2))

    def calibrated(self, v: int, head: Head) -> Head:
        head.calibrate(self.check[v], self.known)
        return head


def _round(store: DataFrame, stage: common.Stage, own: list, past: list, turn: int, confident: float, keep: float = 2e-5) -> list | None:
    """Each head's pair of views, fitted on labelled rows and on all that the other view lends; None if nothing is lent."""
    spark = store.sparkSession
    sent = spark.sparkContext.broadcast(past)
    ks = [(2 * h + v, h, v) for h in range(len(own)) for v in range(2)]
    free = store.filter("NOT own").select("slots", "measures", "meta")

    def counted(b):
        rows = _unpacked(*b.columns[:3])
        lent = _lent(sent.value, rows, confident)
        return {k: _counts(rows[v].take(at), lent[k][at], 1 << _BITS[v]) for k, _, v in ks if len(at := np.flatnonzero(~np.isnan(lent[k])))}

    widths = {k: 2 * (1 << _BITS[v]) + 2 * own[h].fit[v].dense.shape[1] + 2 for k, h, v in ks}
    sums = _summed(free, widths, counted)
    if not any(s[-2] for s in sums.values()):
        return None
    points, weight, ways = {}, {}, {}
    for k, h, v in ks:
        rows, y, m = own[h].fit[v], own[h].y, 1 << _BITS[v]
        weight[k] = min(1.0, len(y) / max(1.0, sums[k][-2]))
        all_of = _counts(rows, y, m) + weight[k] * sums[k]
        n, d = all_of[-2], rows.dense.shape[1]
        seen, bad, share = all_of[:m], all_of[m : 2 * m], all_of[-1] / n
        telling = ((bad - seen * share) ** 2 / (seen * share * (1 - share) + 1e-9) >= TELLING) & (seen >= 3)
        names = np.flatnonzero(telling)
        centre = all_of[2 * m : 2 * m + d] / n
        scale = np.sqrt(np.maximum(0, all_of[2 * m + d : 2 * m + 2 * d] / n - centre**2)) + 1e-6
        points[k] = Point(_BITS[v], names, centre, scale, past[h][-1][v].moved(names, centre, scale))
        curve = np.concatenate([seen[names] / n, np.ones(d + 1)]) / 4
        ways[k] = _Descent(points[k].at, curve + 1e-4), n

    wanted = np.zeros(1 << WORD_BITS, bool)
    for k, _, v in ks:
        if not v:
            wanted[points[k].names] = True
    chosen = spark.sparkContext.broadcast(np.packbits(wanted))

    def labelled(batches):
        """Rows that are lent to any view, with the words that take part."""
        schema = pa.schema([(c, pa.binary()) for c in ("slots", "measures", "meta", "lent")])
        for b in batches:
            if b.num_rows:
                rows = _unpacked(*b.columns)
                lent = _lent(sent.value, rows, confident)
                some = np.flatnonzero(~np.isnan(lent).all(axis=0))
                if len(some):
                    text = rows[0].take(some)
                    keep_slot = np.unpackbits(chosen.value)[text.slots] == 1
                    text = Rows(text.slots[keep_slot], np.concatenate([[0], np.cumsum(keep_slot)])[text.ends], text.dense)
                    yield common.batch(schema, _packed(text), b.column(1).take(pa.array(some)), b.column(2).take(pa.array(some)), [x.tobytes() for x in lent[:, some].T.astype(np.float32)])

    lent = stage.save(free.mapInArrow(labelled, "slots binary, measures binary, meta binary, lent binary"), f"lent{turn}")
    for _ in range(PASSES):
        for k in points:
            points[k].at = ways[k][0].next
        now = spark.sparkContext.broadcast(points)

        def sloped(b, now=now):
            rows = _unpacked(*b.columns[:3])
            labels = np.frombuffer(b"".join(b.column(3).to_pylist()), np.float32).reshape(b.num_rows, -1)
            return {k: now.value[k].slope(rows[v].take(at), labels[at, k].astype(float)) for k, _, v in ks if len(at := np.flatnonzero(~np.isnan(labels[:, k])))}

        got = _summed(lent, {k: len(p.at) + 1 for k, p in points.items()}, sloped)
        for k, h, v in ks:
            way, n = ways[k]
            g = (points[k].slope(own[h].fit[v], own[h].y) + weight[k] * got[k]) / n
            w = np.concatenate([points[k].at[:-1], [0.0]])
            way.told(g[-1] + keep / 2 * (w @ w), g[:-1] + keep * w)
        now.destroy()
    stage.drop(f"lent{turn}")
    out = [[None, None] for _ in own]
    for k, h, v in ks:
        p, w = points[k], ways[k][0].best
        weights = np.zeros(1 << p.bits)
        weights[p.names] = w[: len(p.names)]
        out[h][v] = own[h].calibrated(v, Head(p.bits, weights, w[len(p.names) : -1], float(w[-1]), p.centre, p.scale))
    return out


def co_train(store: DataFrame, stage: common.Stage, own: list, rounds: int = ROUNDS, confident: float = CONFIDENT) -> list:
    """Each head's pair of fitted views."""
    past = [[o.first()] for o in own]
    for turn in range(1, rounds):
        if not own or (more := _round(store, stage, own, past, turn, confident)) is None:
            break
        for pairs, pair in zip(past, more):
            pairs.append(pair)
    return [pairs[-1] for pairs in past]


def _views(b, at: dict) -> tuple[Rows, Rows]:
    get = lambda k: b.column(at[k]).to_pylist() if k in at else [None] * b.num_rows
    meta = [meta_view(*x) for x in zip(get("lang"), get("source"), get("n_chars"))]
    return text_rows(b.column(at["text"]).to_pylist()), Rows.of(meta)


_FIELDS = ("doc_id", "text", "lang", "source", "n_chars")


def features(docs: DataFrame, chosen: DataFrame) -> DataFrame:
    """Packed features of every document; ``own`` marks those of the labelled sample, which carry their labels."""
    schema = pa.schema([("doc_id", pa.int64()), ("own", pa.bool_()), ("tie", pa.int64()), ("quality", pa.int32()), ("toxic", pa.int32()), ("slots", pa.binary()), ("measures", pa.binary()), ("meta", pa.binary())])

    def work(batches):
        for b in batches:
            rows = text_rows(b.column(1).to_pylist())
            meta = [np.array(meta_view(*x), "<u2").tobytes() for x in zip(*(c.to_pylist() for c in b.columns[2:5]))]
            yield common.batch(schema, b.column(0), *b.columns[5:], _packed(rows), [m.tobytes() for m in rows.dense], meta)

    rows = docs.join(F.broadcast(chosen.withColumn("own", F.lit(True))), "doc_id", "left")
    tie = F.when(F.col("own"), F.xxhash64(*_FIELDS))
    rows = rows.select(*_FIELDS, F.coalesce("own", F.lit(False)).alias("own"), tie.alias("tie"), "quality", "toxic")
    return rows.mapInArrow(work, "doc_id long, own boolean, tie long, quality int, toxic int, slots binary, measures binary, meta binary")


def train(docs: DataFrame, labels: DataFrame, labelled: int = LABELLED) -> tuple[Model, DataFrame]:
    """Both views fitted on a sample of labelled rows and on all other rows of docs; the features of docs."""
    common.small_batches(docs.sparkSession)
    docs = common.columns(docs, list(_FIELDS))
    stage = common.Stage(docs.sparkSession, "quality")
    known = labels.filter("doc_id IS NOT NULL").groupBy("doc_id").agg(F.max("quality").cast("int").alias("quality"), F.max("toxic").cast("int").alias("toxic"))
    chosen = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(labelled)
    store = stage.save(features(docs, chosen), "features")
    t = store.filter("own").toArrow().sort_by([("doc_id", "ascending"), ("tie", "ascending")]).combine_chunks()
    views = _unpacked(*(t.column(c).combine_chunks() for c in ("slots", "measures", "meta"))) if t.num_rows else None
    own, at = [], []
    for h, (name, bad) in enumerate((("quality", 0.0), ("toxic", 1.0))):
        value = t.column(name).cast(pa.float64()).to_numpy(zero_copy_only=False) if t.num_rows else np.empty(0)
        have = np.flatnonzero(~np.isnan(value))
        y = (value[have] == bad).astype(float)
        if len(y) >= 10 and y.min() != y.max():
            own.append(_Labelled(tuple(v.take(have) for v in views), y))
            at.append(h)
    heads = [(None, None, 0.0)] * len(HEADS)
    for h, o, pair in zip(at, own, co_train(store, stage, own)):
        heads[h] = (*pair, o.prior)
    return Model(*(list(x) for x in zip(*heads))), store


def _light(head: Head | None) -> Head | None:
    if head is not None:
        head.weights = head.weights.astype(np.float32)
    return head


def score(docs: DataFrame, labels: DataFrame, bound: float = 0.5) -> DataFrame:
    """One row per document: doc_id, probability of low quality and of toxic text, and whether it stays."""
    fitted, store = train(docs, labels)
    model = docs.sparkSession.sparkContext.broadcast(_ready(fitted))

    def work(batches):
        schema = pa.schema([("doc_id", pa.int64()), ("low_quality", pa.float64()), ("toxic", pa.float64()), ("keep", pa.bool_())])
        for b in batches:
            if b.num_rows:
                p = model.value.bad(*_unpacked(*b.columns[1:]))
                yield common.batch(schema, b.column(0), p[0], p[1], (p < bound).all(axis=0))

    return store.select("doc_id", "slots", "measures", "meta").mapInArrow(work, "doc_id long, low_quality double, toxic double, keep boolean")


def _ready(model: Model) -> Model:
    return Model([_light(h) for h in model.text], [_light(h) for h in model.meta], model.prior)


def kept(docs: DataFrame, labels: DataFrame, bound: float = 0.5) -> DataFrame:
    """The documents that stay, with all their columns."""
    model = docs.sparkSession.sparkContext.broadcast(_ready(train(docs, labels)[0]))
    at = {k: docs.columns.index(k) for k in _FIELDS}

    def work(batches):
        for b in batches:
            if b.num_rows:
                p = model.value.bad(*_views(b, at))
                yield b.filter(pa.array((p < bound).all(axis=0)))

    return docs.mapInArrow(work, docs.schema)
