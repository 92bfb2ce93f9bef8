import hashlib
import random

import pytest

from rpqspark.llm import anchors, substrings, suffixes


def sha(x):
    return hashlib.sha256(x).hexdigest()


def brute_words(rows, size=13):
    first, parts = {}, [(d, (t or "").encode().split()) for d, t in rows]
    for d, w in parts:
        for i in range(len(w) - size + 1):
            k = tuple(w[i : i + size])
            if d is not None:
                first[k] = min(first.get(k, d), d)
    out = []
    for d, w in parts:
        gone = set()
        for i in range(len(w) - size + 1):
            if d is not None and first[tuple(w[i : i + size])] < d:
                gone.update(range(i, i + size))
        out.append((d, len(w), len(gone), sha(b" ".join(x for i, x in enumerate(w) if i not in gone))))
    return out


def covered(b, n, size):
    gone = [False] * len(b)
    for i in range(len(b) - size + 1):
        if n[b[i : i + size]] > 1:
            gone[i : i + size] = [True] * size
    return gone


def brute_bytes(rows, size=400):
    n, parts = {}, [(d, (t or "").encode()) for d, t in rows]
    for _, b in parts:
        for i in range(len(b) - size + 1):
            n[b[i : i + size]] = n.get(b[i : i + size], 0) + 1
    out = []
    for d, b in parts:
        gone = covered(b, n, size)
        runs = sum(1 for i, g in enumerate(gone) if g and not (i and gone[i - 1]))
        out.append((d, len(b), sum(gone), runs, sha(bytes(x for x, g in zip(b, gone) if not g))))
    return out


def brute_passages(rows, size=250):
    n, parts = {}, [(t or "").encode() for _, t in rows]
    for b in parts:
        for i in range(len(b) - size + 1):
            n[b[i : i + size]] = n.get(b[i : i + size], 0) + 1
    return [sum(covered(b, n, size)) for b in parts]


def corpus(seed, n=70, words=300):
    rnd = random.Random(seed)
    vocab = [f"wörd{i}" for i in range(400)] + ["The", "a", "of"]
    passages = [[rnd.choice(vocab) for _ in range(rnd.choice([11, 12, 13, 14, 30, 60, 90]))] for _ in range(8)]
    texts = []
    for _ in range(n):
        t = [rnd.choice(vocab) for _ in range(rnd.randrange(words))]
        for _ in range(rnd.randrange(4)):
            p = rnd.choice(passages)
            a = rnd.randrange(len(p))
            at = rnd.randrange(len(t) + 1)
            t[at:at] = p[a // 2 :] if rnd.random() < 0.5 else p
        texts.append(rnd.choice([" ", "  ", "\n"]).join(t))
    base = texts[0].split() + [rnd.choice(vocab) for _ in range(200)]
    for _ in range(12):
        t = list(base)
        for _ in range(rnd.randrange(4)):
            t[rnd.randrange(len(t))] = rnd.choice(vocab)
        texts.append(" ".join(t))
    texts += [None, "", " ", "one", "la " * 900, "la " * 300 + "lo " + "la " * 300, "ab" * 500, "x" * 399, "x" * 400, texts[3], texts[3]]
    rnd.shuffle(texts)
    return texts


@pytest.mark.parametrize("hot", ["no", "sampled", "counted"])
def test_both_equal_brute_force(spark, docs_of, monkeypatch, hot):
    if hot == "counted":  # every gram with over two classes goes by its windows
        monkeypatch.setattr(anchors, "GROUP", 2)
    if hot == "sampled":  # every gram seen in a sample of half is frequent
        monkeypatch.setattr(anchors, "SAMPLE_ONE_IN", 2)
        monkeypatch.setattr(anchors, "SIGHTINGS", 1)
        monkeypatch.setattr(anchors, "PARTITION_SHARE", 0)
    texts = corpus(4)
    ids = list(range(len(texts)))
    random.Random(1).shuffle(ids)
    ids[5] = ids[6]
    ids[7] = None
    rows = list(zip(ids, texts))
    order = lambda x: sorted(x, key=str)
    got = substrings.repeated_words(docs_of(texts, ids), digest=True).collect()
    assert order(tuple(r) for r in got) == order(brute_words(rows))
    got = suffixes.repeated_bytes(docs_of(texts, ids), digest=True).collect()
    want = [(*r, n) for r, n in zip(brute_bytes(rows), brute_passages(rows))]
    assert order(tuple(r) for r in got) == order(want)


def test_passages_are_cut_out_of_the_pipelines_texts(spark, docs_of):
    rnd = random.Random(9)
    words = lambda n: " ".join(f"w{rnd.randrange(10**6)}" for _ in range(n))
    passage, long_one = words(52), words(120)
    texts = [f"{words(40)} {passage} {words(30)}", f"{passage} {words(9)}", f"{words(5)} {long_one}", f"{long_one}", words(60), None, ""]
    got = {r.doc_id: r.text for r in suffixes.without_repeats(docs_of(texts)).collect()}
    n, size = {}, suffixes.PASSAGE
    for b in ((t or "").encode() for t in texts):
        for i in range(len(b) - size + 1):
            n[b[i : i + size]] = n.get(b[i : i + size], 0) + 1
    for i, t in enumerate(texts):
        b = (t or "").encode()
        left = bytes(x for x, g in zip(b, covered(b, n, size)) if not g).decode()
        assert (got[i] or "") == left and (got[i] is None) == (t is None)
    assert got[4] == texts[4] and passage not in got[0] + got[1] and long_one not in got[2]


def test_a_tree_lists_maximal_repeats():
    words = [x.split() for x in (b"a b c d", b"a b c e", b"a b x", b"q", b"a b c d")]
    tree = substrings.Subtree(words)
    found = {(d, tuple(sorted(below))) for d, below in tree.repeats}
    assert found == {(0, (0, 1, 2, 3, 4)), (2, (0, 1, 2, 4)), (3, (0, 1, 4)), (4, (0, 4))}
    rnd = random.Random(3)
    for _ in range(300):
        pool = [[rnd.choice([b"a", b"b"]) for _ in range(8)] for _ in range(3)]
        some = [rnd.choice(pool)[: rnd.randrange(9)] + [rnd.choice([b"a", b"c"])] * rnd.randrange(3) for _ in range(rnd.randrange(1, 9))]
        tree = substrings.Subtree(some)
        for depth in range(1, 10):
            of = tree.classes(depth)
            for i, a in enumerate(some):
                for j, b in enumerate(some):
                    same = i == j or len(a) >= depth and len(b) >= depth and a[:depth] == b[:depth]
                    assert (of[i] == of[j]) == same


def test_empty(spark, docs_of):
    assert substrings.repeated_words(docs_of([])).collect() == []
    assert suffixes.repeated_bytes(docs_of([])).collect() == []


def test_deep_shallow_order():
    rnd = random.Random(2)
    for _ in range(300):
        pool = [bytes(rnd.choice(b"ab") for _ in range(rnd.randrange(60))) for _ in range(4)]
        strings = [rnd.choice(pool)[: rnd.randrange(61)] + bytes(rnd.choice(b"abc") for _ in range(rnd.randrange(30))) for _ in range(rnd.randrange(1, 12))]
        order, lcp = suffixes.deep_shallow(strings)
        assert [strings[i] for i in order] == sorted(strings) and sorted(order) == list(range(len(strings)))
        for k in range(1, len(order)):
            a, b = strings[order[k - 1]], strings[order[k]]
            assert lcp[k] == next((i for i, (x, y) in enumerate(zip(a, b)) if x != y), min(len(a), len(b)))


def test_long_text_in_blocks(monkeypatch):
    import numpy as np

    rnd = np.random.default_rng(0)
    symbols = rnd.integers(0, 2**63, 5000, dtype=np.uint64)
    whole = anchors.anchors(symbols, substrings.RULE)
    monkeypatch.setattr(anchors, "BLOCK", 512)
    assert all((a == b).all() for a, b in zip(whole, anchors.anchors(symbols, substrings.RULE)))
