import math

import numpy as np
import pytest
from pyspark.sql import types as T

from rpqspark.llm import neighbours, products

ROW = T.StructType([T.StructField("vec_id", T.LongType()), T.StructField("embedding", T.ArrayType(T.FloatType())), T.StructField("label", T.IntegerType()), T.StructField("turn", T.StringType())])


def table(spark, vectors, ids=None):
    return spark.createDataFrame([((i if ids is None else ids[i]), None if v is None else [None if x is None else float(x) for x in v], 1, "x") for i, v in enumerate(vectors)], ROW)


def made(n=700, dim=24, seed=0, lengths=False):
    rng = np.random.default_rng(seed)
    x = rng.standard_normal((n, dim)).astype(np.float32)
    if not lengths:
        x /= np.linalg.norm(x, axis=1, keepdims=True)
    else:
        x *= rng.exponential(1, (n, 1)).astype(np.float32)
    out = [list(map(float, v)) for v in x]
    out[50:70] = [out[50]] * 20
    out[3], out[200], out[5], out[6], out[300] = None, [0.0] * dim, [float("nan")] + out[5][1:], [None] + out[6][1:], [float("inf")] + out[300][1:]
    return out


def good(v):
    return v is not None and all(x is not None and math.isfinite(x) for x in v)


def test_nearest_recall_and_scores(spark):
    vs = made()
    rows = neighbours.nearest(table(spark, vs)).collect()
    ok = {i: np.array(v, np.float32).astype(float) for i, v in enumerate(vs) if good(v) and any(v)}
    hits = total = 0
    by = {}
    for r in rows:
        by.setdefault(r.query_id, []).append(r)
    assert set(by) == {i for i in ok if i % 100 == 0}
    for q, found in by.items():
        found.sort(key=lambda r: r["rank"])
        assert [r["rank"] for r in found] == list(range(1, 11))
        for r in found:
            assert r.score == pytest.approx(float(np.sqrt(((ok[q] - ok[r.vec_id]) ** 2).sum())), abs=1e-12)
        assert [(r.score, r.vec_id) for r in found] == sorted((r.score, r.vec_id) for r in found)
        want = sorted((float(np.sqrt(((ok[q] - v) ** 2).sum())), i) for i, v in ok.items() if i != q)[:10]
        hits += len({i for _, i in want} & {r.vec_id for r in found})
        total += 10
    assert hits / total >= 0.9


@pytest.mark.parametrize("lengths", [False, True])
def test_largest_products_are_exact(spark, lengths):
    vs = made(lengths=lengths)
    got = sorted(tuple(r) for r in products.largest(table(spark, vs)).collect())
    ok = {i: [math.floor(256 * float(np.float32(x))) for x in v] for i, v in enumerate(vs) if good(v)}
    want = []
    for q in ok:
        if q % 50 == 0:
            s = sorted((-sum(a * b for a, b in zip(ok[q], v)), i) for i, v in ok.items() if i != q)[:5]
            want += [(q, n + 1, i, -p) for n, (p, i) in enumerate(s)]
    assert got == sorted(want)


def test_coordinate_pruning_is_exact():
    rng = np.random.default_rng(1)
    centre = rng.standard_normal(16)
    base = np.concatenate([centre + 0.05 * rng.standard_normal((300, 16)), rng.standard_normal((900, 16))])
    queries = centre + 0.05 * rng.standard_normal((20, 16))
    ids, q_ids = np.arange(1200), np.arange(2000, 2020)
    q, i, s = products.buckets(ids, base, q_ids, queries)
    b, a = np.floor(base * 256).astype(int), np.floor(queries * 256).astype(int)
    for j in range(20):
        want = sorted(zip((-(b @ a[j])).tolist(), ids.tolist()))[:5]
        assert list(zip((-s[q == 2000 + j]).tolist(), i[q == 2000 + j].tolist())) == want


def test_few_huge_and_empty(spark):
    assert neighbours.nearest(table(spark, [])).collect() == [] == products.largest(table(spark, [])).collect()
    one = table(spark, [[1e30, 2.0], [3.0, 1e30], [1.0, 1.0], [5.0]], ids=[0, 1, 2, None])
    assert [(r.query_id, r["rank"], r.vec_id) for r in sorted(products.largest(one).collect())] == [(0, 1, 1), (0, 2, 2)]
    assert len(neighbours.nearest(one).collect()) == 2


def test_short_vectors_are_never_met(spark, monkeypatch):
    """Vectors of very different lengths: exact, and no short block reaches a query."""
    rng = np.random.default_rng(8)
    x = rng.standard_normal((900, 8)).astype(np.float32)
    x[40:] *= 0.001
    seen = []
    inner = products.vectors.met

    def spy(rows, asked, nearest, prepare, find, reach=False):
        if reach:
            packed = products.vectors.blocks(rows, products.vectors.BLOCK_VECTORS).agg({"extreme": "max"}).first()[0]
            seen.append((packed, [r.extreme for r in asked.collect()]))
        return inner(rows, asked, nearest, prepare, find, reach)

    monkeypatch.setattr(products.vectors, "met", spy)
    got = sorted(tuple(r) for r in products.largest(table(spark, x.tolist()), every=10).collect())
    whole, want = np.floor(x.astype(float) * 256).astype(int), []
    for q in range(0, 900, 10):
        s = sorted((-int(whole[q] @ whole[i]), i) for i in range(900) if i != q)[:5]
        want += [(q, n + 1, i, -p) for n, (p, i) in enumerate(s)]
    assert got == sorted(want) and len(seen) == 1 and seen[0][0] > 0


def test_recall_on_the_given_vectors(spark, sf_dir):
    given = spark.read.parquet(f"{sf_dir.replace('0.001', '0.01')}/embeddings.parquet")
    rows = [(r.vec_id, np.array(r.embedding, float)) for r in given.collect() if r.embedding]
    ids, x = np.array([i for i, _ in rows]), np.stack([v for _, v in rows])
    got = {}
    for r in neighbours.nearest(given).collect():
        got.setdefault(r.query_id, set()).add(r.vec_id)
    hits = total = 0
    for q, found in got.items():
        d = np.sqrt(((x - x[ids == q][0]) ** 2).sum(axis=1))
        near = [i for i in ids[np.lexsort((ids, d))].tolist() if i != q][:10]
        hits, total = hits + len(found & set(near)), total + 10
    assert hits >= 0.9 * total


@pytest.mark.parametrize("search", [neighbours.nearest, products.largest])
def test_copies_of_queries_do_not_grow_with_the_partitions(spark, search):
    """However many partitions a shuffle has, queries are copied a bounded number of times, and not by way of the driver."""
    was = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "600")
    try:
        plan = search(table(spark, made(n=400, dim=4)))._jdf.queryExecution().toString()
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", was)
    assert "BroadcastExchange" not in plan and "Join" not in plan


def test_groups_of_queries_are_exact(spark, monkeypatch):
    """Queries beyond what a task holds meet every block in groups."""
    vectors = products.vectors
    x = np.random.default_rng(5).standard_normal((640, 8)).astype(np.float32)
    want = [sorted(tuple(r) for r in f(table(spark, x.tolist()), every=4).collect()) for f in (neighbours.nearest, products.largest)]
    monkeypatch.setattr(vectors, "HELD", 3000)
    monkeypatch.setattr(vectors, "BLOCK_QUERIES", 10)
    monkeypatch.setattr(vectors, "BLOCK_VECTORS", 50)
    monkeypatch.setattr(vectors, "COPIES", 3)
    assert sorted(tuple(r) for r in products.largest(table(spark, x.tolist()), every=4).collect()) == want[1]
    got = sorted(tuple(r) for r in neighbours.nearest(table(spark, x.tolist()), every=4).collect())
    d = {(q, i): float(np.sqrt(((x[q].astype(float) - x[i].astype(float)) ** 2).sum())) for q, _, i, _ in got}
    assert len(got) == len(want[0]) and all(s == pytest.approx(d[q, i], abs=1e-12) for q, _, i, s in got)
    assert len({r[:3:2] for r in got} & {r[:3:2] for r in want[0]}) >= 0.9 * len(got)


def exact(x, every, k=5):
    whole, want = [[math.floor(256 * float(a)) for a in v] for v in x], []
    for q in range(0, len(x), every):
        s = sorted((-sum(a * b for a, b in zip(whole[q], v)), i) for i, v in enumerate(whole) if i != q)[:k]
        want += [(q, n + 1, i, -p) for n, (p, i) in enumerate(s)]
    return sorted(want)


def test_copies_and_blocks_do_not_multiply_what_is_found(spark, monkeypatch):
    """A task gives k rows a query, however many blocks it meets, and of equal vectors only as many are met as can be among the best."""
    vectors, inner, met = products.vectors, products.vectors.met, []
    x = np.random.default_rng(9).standard_normal((60, 8)).astype(np.float32)
    x = np.concatenate([x] * 15 + [x[:1]] * 300)

    def spy(rows, asked, nearest, prepare, find, reach=False):
        out = inner(rows, asked, nearest, prepare, find, reach)
        met.append((rows.count(), out.count()))
        return out

    monkeypatch.setattr(vectors, "met", spy)
    monkeypatch.setattr(vectors, "BLOCK_VECTORS", 8)
    monkeypatch.setattr(vectors, "COPIES", 2)
    got = sorted(tuple(r) for r in products.largest(table(spark, x.tolist()), every=50).collect())
    assert got == exact(x, 50)
    assert sum(n for n, _ in met) <= 60 * 6 and all(found <= 24 * 5 * 2 for _, found in met)


@pytest.mark.parametrize("scale", [1, 30, 300, 1e5, 1e6])
def test_products_of_every_size_are_exact(spark, scale):
    """Whole numbers of two bytes and more, sums that single precision, double precision or neither holds."""
    x = np.random.default_rng(10).standard_normal((300, 6)).astype(np.float32)
    x[::3] *= np.float32(scale)
    assert sorted(tuple(r) for r in products.largest(table(spark, x.tolist()), every=20).collect()) == exact(x, 20)


def test_buckets_far_in_a_coordinate_are_left_out():
    rng = np.random.default_rng(11)
    centre = rng.standard_normal((8, 32))
    centre *= 500 / np.linalg.norm(centre, axis=1, keepdims=True)
    base = np.floor(np.repeat(centre, 256, axis=0) + rng.standard_normal((2048, 32)))
    queries = np.floor(centre[:1] + rng.standard_normal((20, 32)))
    search, ids = products.Search(5), np.arange(2048)
    best, seen, inner = search.start(np.arange(3000, 3020), queries), [], search._products
    search.meet(products.Buckets(ids[:256], base[:256]), best)
    best.rank()
    search._products = lambda b, i, *rest: (seen.append(len(i)), inner(b, i, *rest))
    search.meet(products.Buckets(ids, base), best)
    assert seen == [256]
