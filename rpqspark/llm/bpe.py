"""Byte-pair encoding by a contiguous array of ranks, and decoding.

A word is held as two short arrays that lie side by side: its parts, and the
rank of the merge of each part with its right neighbour. The smallest rank is
found by a scan, the boundary at it is deleted, and the two ranks beside it are
looked up anew; words are short, so a scan beats a heap. A word of more than ``LONG`` parts
goes by a heap of ranks over linked parts, which gives the same merges in the same order.
Words that were seen before come from a bounded table of finished words.

Nulls count as empty text. Special tokens that stand in a text are matched as
the tokenizers library does by default. Any text length is encoded whole.
"""

from __future__ import annotations

import functools
import hashlib
import heapq
import json
import re

import pyarrow as pa
from pyspark.sql import DataFrame

from . import common

#: Rank of a pair that no merge joins.
NONE = 1 << 60
#: Parts up to which a word is scanned.
LONG = 256
#: Finished words that a worker holds before it forgets them all.
WORD_TABLE = 150_000
#: Characters whose classes and lower case agree in every library used here.
PLAIN = re.compile("[^\\t-\\r -\\xb1\\xb4-\\xb8\\xba\\xbb\\xbf-\\u012f\\u0132-\\u0148\\u014a-\\u024f\\u2010-\\u2027\\u2030-\\u205e\\u20a0-\\u20bf]")
#: Letters among them and their lower case; their digits are 0-9.
LETTERS = "A-Za-z\xaa\xb5\xba\xc0-\xd6\xd8-\xf6\xf8-\u02af\u2c65\u2c66"


@functools.cache
def byte_characters() -> list[str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    own = {*range(33, 127), *range(161, 173), *range(174, 256)}
    rest = iter(range(256, 512))
    return [chr(b) if b in own else chr(next(rest)) for b in range(256)]


class Bpe:
    """A vocabulary with merges, read from a file of the tokenizers library."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            made = json.load(f)
        model = made["model"]
        self.vocab: dict[str, int] = model["vocab"]
        self.suffix: str = model.get("end_of_word_suffix") or ""
        self.special = {t["content"]: t["id"] for t in made["added_tokens"]}
        self.at_special = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.names = {i: t for t, i in self.vocab.items()} | {i: t for t, i in self.special.items()}
        self.merge: dict[tuple[int, int], tuple[int, int]] = {}
        for rank, pair in enumerate(model["merges"]):
            a, b = pair if isinstance(pair, list) else pair.split(" ")
            self.merge[self.vocab[a], self.vocab[b]] = (rank, self.vocab[a + b])
        self.lower = "Lowercase" in json.dumps(made["normalizer"])
        self.byte_level_decoder = made["decoder"] is not None
        if self.suffix:
            self.plain = re.compile(rf"[{LETTERS}]+|[0-9]|'(?:s|t|re|ve|m|ll|d)|[^\s0-9{LETTERS}]+")
        else:
            self.plain = re.compile(rf" ?[{LETTERS}]+|'(?:s|t|re|ve|m|ll|d)| ?[0-9]+| ?[^\s0-9{LETTERS}]+|\s+(?!\S)|\s+")
        self.to_char = byte_characters()
        self.translate = {b: c for b, c in enumerate(self.to_char)}

    def pieces(self, text: str) -> tuple[list[str], bool]:
        """The words of a text without special tokens; whether they are byte characters already."""
        if PLAIN.search(text) is None:
            return self.plain.findall(text.lower() if self.lower else text), False
        if self.library.normalizer is not None:
            text = self.library.normalizer.normalize_str(text)
        return [p for p, _ in self.library.pre_tokenizer.pre_tokenize_str(text)], True

    def spelled(self, word: str) -> str:
        return word.encode().decode("latin-1").translate(self.translate)

    def word(self, spelled: str) -> list[int]:
        """Ids of one word, given in byte characters."""
        if not spelled:
            return []
        vocab, merge = self.vocab, self.merge
        parts = [vocab[c] for c in spelled[:-1]]
        parts.append(vocab[spelled[-1] + self.suffix])
        if len(parts) > LONG:
            return self.long_word(parts)
        ranks = [merge.get(p, (NONE, 0))[0] for p in zip(parts, parts[1:])]
        while ranks:
            least = min(ranks)
            if least == NONE:
                break
            i = ranks.index(least)
            parts[i] = merge[parts[i], parts[i + 1]][1]
            del parts[i + 1], ranks[i]
            if i < len(ranks):
                ranks[i] = merge.get((parts[i], parts[i + 1]), (NONE, 0))[0]
            if i:
                ranks[i - 1] = merge.get((parts[i - 1], parts[i]), (NONE, 0))[0]
        return parts

    def long_word(self, parts: list[int]) -> list[int]:
        """The merges of a long word: the least rank first, the leftmost of equal ones."""
        merge, n = self.merge, len(parts)
        parts, ahead, behind = [*parts, -1], [*range(1, n + 1), n], [*range(-1, n)]
        heap = [(merge[p][0], i, *p) for i, p in enumerate(zip(parts, parts[1:n])) if p in merge]
        heapq.heapify(heap)
        while heap:
            _, i, left, right = heapq.heappop(heap)
            j = ahead[i]
            if parts[i] != left or parts[j] != right:
                continue  # one of the two was merged meanwhile
            parts[i], parts[j] = merge[left, right][1], -1
            k = ahead[i] = ahead[j]
            behind[k] = i
            for a, b in ((i, k), (behind[i], i)):
                if a >= 0 and (pair := (parts[a], parts[b])) in merge:
                    heapq.heappush(heap, (merge[pair][0], a, *pair))
        return [p for p in parts if p >= 0]

    def spans(self, text: str):
        """Stretches of a text between special tokens, and the special tokens."""
        return self.at_special.split(text) if self.at_special is not None and self.at_special.search(text) else (text,)

    def encode(self, text: str) -> list[int]:
        out: list[int] = []
        for s in self.spans(text):
            if s in self.special:
                out.append(self.special[s])
                continue
            found, spelled = self.pieces(s)
            for w in found:
                out += self.word(w if spelled else self.spelled(w))
        return out

    def decode(self, ids: list[int]) -> str:
        """Text of ids as the library gives it with special tokens kept."""
        names = self.names
        if not self.byte_level_decoder:
            return " ".join(names[i] for i in ids if i in names)
        back = {c: b for b, c in enumerate(self.to_char)}
        return bytes(back[c] for i in ids if i in names for c in names[i]).decode("utf-8", "replace")


class Finished(dict):
    """Finished words: the value of a word is made once and kept, up to a bound.

    A full table becomes the older one; words used again move on, others are forgotten.
    """

    def __init__(self, make, most: int = WORD_TABLE):
        self.make, self.most, self.older = make, most, {}

    def __missing__(self, word: str):
        if len(self) >= self.most:
            self.older = dict(self)
            self.clear()
        value = self.older.get(word)
        if value is None:
            value = self.make(word)
        if len(word) < 64:
            self[word] = value
        return value


@functools.cache
def load(path: str) -> Bpe:
    return Bpe(path)


ENCODED = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids", pa.string()), ("decoded", pa.string())])


class Joined:
    """Texts to (number of ids, ids joined by spaces, decoded tokens joined by spaces)."""

    def __init__(self, path: str):
        self.bpe = load(path)
        names, word, spelled = self.bpe.names, self.bpe.word, self.bpe.spelled

        def made(w: str):
            ids = word(w)
            return len(ids), " ".join(map(str, ids)), " ".join([names[i] for i in ids])

        self.own, self.raw = Finished(lambda w: made(spelled(w))), Finished(made)

    def __call__(self, text: str | None) -> tuple[int, str, str]:
        n, ids, tokens = 0, [], []
        for s in self.bpe.spans(text or ""):
            if s in self.bpe.special:
                n += 1
                ids.append(str(self.bpe.special[s]))
                tokens.append(s)
                continue
            found, spelled = self.bpe.pieces(s)
            if found:
                table = self.raw if spelled else self.own
                a, b, c = zip(*map(table.__getitem__, found))
                n += sum(a)
                ids.append(" ".join(b))
                tokens.append(" ".join(c))
        return n, " ".join(ids), " ".join(tokens)


def encode_decode(docs: DataFrame, tokenizer: str, digest: bool = False) -> DataFrame:
    """One row per document: ids joined by spaces and the decoded text.

    ``digest``: SHA-256 of both instead, made where the text is, so that only
    digests leave the worker. The vocabulary must be one without a decoder, whose
    decoded text is its tokens joined by spaces; other vocabularies decode with
    :meth:`Bpe.decode`. Null text is empty; repeated rows stay; an empty table
    gives an empty one.
    """
    common.small_batches(docs.sparkSession)
    names = ("ids_sha256", "decoded_sha256") if digest else ("ids", "decoded")

    def work(batches):
        encode, bpe = Joined(tokenizer), load(tokenizer)
        schema = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), (names[0], pa.string()), (names[1], pa.string())])
        for b in batches:
            n, ids, out = [], [], []
            for text in b.column(1):
                a, i, d = encode(text.as_py())
                if bpe.byte_level_decoder:
                    d = bpe.decode([int(x) for x in i.split()])
                n.append(a)
                ids.append(hashlib.sha256(i.encode()).hexdigest() if digest else i)
                out.append(hashlib.sha256(d.encode()).hexdigest() if digest else d)
            yield common.batch(schema, b.column(0), n, ids, out)

    return common.columns(docs, ["doc_id", "text"]).mapInArrow(work, f"doc_id long, n_tokens long, {names[0]} string, {names[1]} string")
