import hashlib
import zlib

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from rpqspark.llm import bpe, packing

TEXTS = [
    "", None, " ", "a", "It's the DOG's 12 34ths, we'll see…", "naïve ÉTÉ Straße ÀÉ", "x" * 3000, "tab\tnew\n\n  line  thin", "日本語 テキスト ² ½ Ⅷ", "ΣΑΣ ΟΔΟΣ ok",
    "mix <|endoftext|> in <|startoftext|>text<|endoftext|>", "été combining", "İstanbul ŉ ǅ", "___ __init__ a_b", "\x1c\x1d a\x85b", "🙂🙂 !!??", "line\r\n\r\n end   ", "don't 'S 's 'RE", "a\x00b",
]


@pytest.mark.parametrize("file", ["word_bpe_49k.json", "byte_bpe_50k.json"])
def test_ids_and_text_equal_the_library(file):
    path = public_tokenizers.path(file)
    own, lib = bpe.Bpe(path), Tokenizer.from_file(path)
    for t in TEXTS:
        want = lib.encode(t or "", add_special_tokens=False).ids
        assert own.encode(t or "") == want, t
        assert own.decode(want) == lib.decode(want, skip_special_tokens=False), t


def test_query_rows(spark, docs_of):
    path = public_tokenizers.path("word_bpe_49k.json")
    lib = Tokenizer.from_file(path)
    got = {r.doc_id: r for r in bpe.encode_decode(docs_of(TEXTS), path, digest=True).collect()}
    for i, t in enumerate(TEXTS):
        ids = lib.encode(t or "", add_special_tokens=False).ids
        text = lib.decode(ids, skip_special_tokens=False)
        assert (got[i].n_tokens, got[i].ids_sha256, got[i].decoded_sha256) == (len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(text.encode()).hexdigest())
    assert bpe.encode_decode(docs_of([]), path).collect() == []


def test_packing_whole_and_dense(spark, docs_of):
    path = public_tokenizers.path("byte_bpe_50k.json")
    lib = Tokenizer.from_file(path)
    texts = TEXTS + ["word " * n for n in range(0, 5000, 61)] + ["word " * 4000] * 2
    got = packing.best_fit(docs_of(texts), path, 2048, group_pieces=50).collect()
    by, bins = {}, {}
    for r in got:
        by.setdefault(r.doc_id, []).append(r)
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    assert len(by) == len(texts)
    for i, t in enumerate(texts):
        ids = lib.encode(t or "", add_special_tokens=False).ids + [0]
        rows = sorted(by[i], key=lambda r: r.piece)
        assert [r.piece for r in rows] == list(range(len(rows)))
        assert sum(r.length for r in rows) == len(ids) and all(r.length == 2048 for r in rows[1:])
        for r in rows:
            assert r.ids_crc32 == zlib.crc32(np.array(ids[r.start : r.start + r.length], "<u4").tobytes())
    for rows in bins.values():
        rows.sort()
        assert all(o == sum(n for _, n in rows[:k]) for k, (o, _) in enumerate(rows)) and sum(n for _, n in rows) <= 2048


def test_fullest_combination():
    rng = np.random.default_rng(1)
    for _ in range(200):
        lengths = rng.integers(1, 30, rng.integers(1, 9)).tolist()
        room = int(rng.integers(1, 60))
        counts = {n: lengths.count(n) for n in lengths}
        best = max(s for m in range(1 << len(lengths)) if (s := sum(n for i, n in enumerate(lengths) if m >> i & 1)) <= room)
        chosen = packing.fill(sorted(counts, reverse=True), counts, room)
        assert sum(chosen) == best and all(chosen.count(n) <= counts[n] for n in chosen)


def test_random_characters_of_the_plain_range():
    import random

    rnd = random.Random(1)
    pool = [chr(i) for i in [*range(9, 14), *range(32, 0x250), *range(0x2010, 0x205F), *range(0x20A0, 0x20C0)]] + list("  ''strevmld") * 8
    for file in ("word_bpe_49k.json", "byte_bpe_50k.json"):
        path = public_tokenizers.path(file)
        own, lib = bpe.Bpe(path), Tokenizer.from_file(path)
        for _ in range(1500):
            t = "".join(rnd.choice(pool) for _ in range(rnd.randrange(1, 30)))
            assert own.encode(t) == lib.encode(t, add_special_tokens=False).ids, ascii(t)


def test_long_words_merge_alike_and_in_time():
    import random
    import time

    rnd = random.Random(5)
    for file in ("word_bpe_49k.json", "byte_bpe_50k.json"):
        path = public_tokenizers.path(file)
        own, lib = bpe.Bpe(path), Tokenizer.from_file(path)
        for letters in ("ab", "theandrsio", "a"):
            t = "".join(rnd.choice(letters) for _ in range(3000))
            assert own.encode(t) == lib.encode(t, add_special_tokens=False).ids
        t = "".join(rnd.choice("etaoinshrdlu") for _ in range(40_000))
        began = time.process_time()
        ids = own.encode(t)
        assert time.process_time() - began < 2 and ids == lib.encode(t, add_special_tokens=False).ids


def test_packing_odd_rows(spark, docs_of):
    path = public_tokenizers.path("byte_bpe_50k.json")
    assert packing.best_fit(docs_of([]), path).collect() == []
    docs = docs_of(["a b", None, "a b", ""], [None, 1, None, 1]).withColumns({"piece": F.lit(9), "length": F.lit("x"), "_group": F.lit(0)})
    got = packing.best_fit(docs, path).collect()
    assert sorted(str((r.doc_id, r.piece, r.length)) for r in got) == sorted(str(x) for x in [(None, 0, 3), (1, 0, 1), (None, 0, 3), (1, 0, 1)])
    assert len({r.sequence_id for r in got}) == 1
