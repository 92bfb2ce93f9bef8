"""Near duplicates at a similarity of 0.8 over five-word shingles, against all pairs."""

import random

import numpy as np
import pytest

from rpqspark.llm import simhash


def brute(texts, similarity=0.8):
    """Group number of each text by exact sets of shingles and all pairs."""
    sets = []
    for t in texts:
        w = (t or "").encode().lower().split()
        sets.append(frozenset(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))) if w else frozenset())
    of = list(range(len(texts)))

    def find(x):
        while of[x] != x:
            x = of[x]
        return x

    for i, a in enumerate(sets):
        for j in range(i):
            b = sets[j]
            if a == b or a and b and len(a & b) >= similarity * len(a | b):
                of[find(i)] = find(j)
    return [find(i) for i in range(len(texts))]


def corpus(seed=3):
    rnd = random.Random(seed)
    words = lambda n: [f"w{rnd.randrange(3000)}" for _ in range(n)]
    texts = []
    for _ in range(60):
        base = words(rnd.choice([40, 90, 300]))
        texts.append(" ".join(base))
        for _ in range(rnd.choice([0, 0, 1, 3])):
            t = list(base)
            for _ in range(rnd.choice([0, 1, 2, len(t) // 60, len(t) // 10])):
                t[rnd.randrange(len(t))] = "changed"
            texts.append(rnd.choice([" ", "  "]).join(t).title() if rnd.random() < 0.3 else " ".join(t))
    hot = words(200)
    for i in range(120):
        t = list(hot)
        t[rnd.randrange(200)] = f"x{i}"
        texts.append(" ".join(t))
    return [*texts, None, "", "  ", "one two", "one  TWO", "one", "la " * 500, "la " * 480]


def test_groups_equal_all_pairs(spark, docs_of):
    texts = corpus()
    got = simhash.one_of_each(docs_of(texts)).collect()
    want = brute(texts)
    least = sorted(want.index(g) for g in set(want))
    assert sorted(r.doc_id for r in got) == least
    assert all(r.text == texts[r.doc_id] for r in got) and got[0].asDict().keys() == docs_of(["a"]).first().asDict().keys()


@pytest.mark.parametrize("sent", [0, 500_000])
def test_odd_rows(spark, docs_of, monkeypatch, sent):
    monkeypatch.setattr(simhash, "SENT", sent)
    ids = [5, 3, 3, None, 9, 2, None, 3, 3]
    texts = ["a b c d", "a b c d", "a b c d", "zz yy xx ww vv", None, "", "another text without an id of its own", "this one shares an id", "this one shares an id"]
    got = simhash.one_of_each(docs_of(texts, ids)).collect()
    assert sorted(str((r.doc_id, r.text)) for r in got) == sorted(str(x) for x in [(3, "a b c d"), (None, texts[3]), (2, ""), (None, texts[6]), (3, texts[7])])
    assert simhash.one_of_each(docs_of([])).collect() == []


def test_chain_filter_loses_none():
    rnd = np.random.default_rng(1)
    base = rnd.integers(0, 2**63, 4, dtype=np.uint64)
    others = []
    for n in rnd.integers(0, 90, 400):
        bits = np.zeros(256, np.uint8)
        bits[rnd.permutation(256)[:n]] = 1
        others.append(base ^ np.packbits(bits, bitorder="little").view(np.uint64))
    others = np.array(others)
    apart = np.bitwise_count(others ^ base).sum(axis=1)
    assert simhash.near(base, others).tolist() == np.flatnonzero(apart <= simhash.NEAR).tolist()


def test_sketch_keys_meet_as_often_as_sets_are_alike():
    rnd = np.random.default_rng(2)
    same = total = 0
    for _ in range(60):
        pool = rnd.integers(0, 2**63, 450, dtype=np.uint64)
        a, b = np.sort(pool[:425]), np.sort(pool[25:])
        a, b = simhash.sketch(a), simhash.sketch(b)
        same += int((a[2] == b[2]).sum())
        total += len(a[2])
    assert abs(same / total - (400 / 450) ** simhash.ROWS) < 0.06
