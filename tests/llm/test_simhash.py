import random

import xxhash

from rpqspark.llm import simhash


def brute(rows):
    """fingerprint and component of each (doc_id, text), by all pairs."""
    def fp(text):
        words, out = [], 0
        w = ""
        for ch in (text or "") + " ":
            if ch in " \t\n\v\f\r":
                if w:
                    words.append(w)
                w = ""
            else:
                w += ch.lower() if "A" <= ch <= "Z" else ch
        sh = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))] if words else []
        hs = [xxhash.xxh64_intdigest(s.encode(), 42) for s in sh]
        for b in range(64):
            if 2 * sum(h >> b & 1 for h in hs) > len(hs):
                out |= 1 << b
        return out

    fps = [fp(t) for _, t in rows]
    up = list(range(len(rows)))

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= 3:
                up[find(i)] = find(j)
    least = {}
    for i, (d, _) in enumerate(rows):
        least[find(i)] = min(least.get(find(i), d), d)
    return sorted((d, f"{fps[i]:016x}", least[find(i)]) for i, (d, _) in enumerate(rows))


def test_equals_brute_force(spark, docs_of):
    rnd = random.Random(3)
    words = ["The", "of", "straße", "AND", "Été", "x y"] + [f"w{i}" for i in range(40)]
    texts = [None, "", " \t\n", "one", "One two", "one  TWO three", "a b c d", "a b c d"]
    base = [rnd.choice(words) for _ in range(200)]
    for _ in range(60):
        t = list(base)
        for _ in range(rnd.randrange(5)):
            t[rnd.randrange(len(t))] = rnd.choice(words)
        texts.append(" ".join(t))
    texts += [" ".join(rnd.choice(words) for _ in range(rnd.randrange(1, 60))) for _ in range(60)] + ["w " * 30000]
    ids = [1000 - i for i in range(len(texts))]
    got = sorted(tuple(r) for r in simhash.groups(docs_of(texts, ids)).collect())
    assert got == brute(list(zip(ids, texts)))


def test_dense_fingerprints_link_whole(spark):
    """Fingerprints planted around a centre, against all pairs."""
    rnd = random.Random(5)
    centre = rnd.getrandbits(64)
    made = {centre}
    while len(made) < 400:
        x = rnd.choice(sorted(made)) if rnd.random() < 0.5 else centre
        for _ in range(rnd.randrange(1, 5)):
            x ^= 1 << rnd.randrange(64)
        made.add(x)
    made |= {rnd.getrandbits(64) for _ in range(50)}
    made = sorted(made)
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    found = spark.createDataFrame([(signed(x),) for x in made], "fp long")
    pairs = simhash.links(found).collect()
    assert len(pairs) < 12 * len(made)
    up = {signed(x): signed(x) for x in made}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in pairs:
        assert ((a ^ b) & (1 << 64) - 1).bit_count() <= 3
        up[find(a)] = find(b)
    for i, x in enumerate(made):
        for y in made[:i]:
            if (x ^ y).bit_count() <= 3:
                assert find(signed(x)) == find(signed(y))


def test_empty_and_null_ids(spark):
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert simhash.groups(empty).collect() == []
    rows = spark.createDataFrame([(None, "a b c"), (7, "a b c"), (7, "a b c"), (None, "zz yy xx ww")], "doc_id long, text string")
    got = sorted((tuple(r) for r in simhash.groups(rows).collect()), key=str)
    assert [r[2] for r in got if r[0] == 7] == [7, 7] and len(got) == 4
