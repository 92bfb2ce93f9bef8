"""The printed index of the worked example, wavelet operations, and the AND rule for inner nodes."""

import random

import numpy as np

from rpqspark import queries
from rpqspark.graph.encode import inverse_id
from rpqspark.index import bits, cyclic, io, wavelet

L = {"o": [3, 4, 2, 4, 3, 5, 4, 1, 2, 1, 1, 5, 1, 2, 2, 4], "s": [3, 5, 2, 2, 3, 1, 4, 1, 5, 4, 4, 1, 2, 2, 4, 1], "p": [5, 2, 3, 4, 4, 1, 5, 1, 2, 1, 3, 5, 4, 3, 1, 3]}


def test_columns_steps_and_ranges(spark, tmp_path):
    index = cyclic.build(queries.metro_numbers(spark))
    for c, want in L.items():
        assert [r.symbol for r in index.columns[c].orderBy("pos").collect()] == want
    at = lambda p: spark.createDataFrame([(p,)], "pos long")
    assert index.lf(at(16), "p").first().next == 10
    assert index.lf(at(10), "s").first().next == 12
    assert index.lf(at(12), "o").first().next == 16
    assert index.lf(at(5), "p").first().next == 12
    ask = spark.createDataFrame([(11, 14, 3), (15, 16, 3), (11, 14, 5), (1, 4, 5)], "b long, e long, symbol long")
    got = {(r.b, r.symbol): (r.nb, r.ne) for r in index.backward(ask, "p").collect()}
    assert got == {(11, 3): (8, 9), (15, 3): (10, 10), (11, 5): (16, 16), (1, 5): (14, 14)}
    assert {r.symbol for r in index.columns["s"].filter("pos BETWEEN 8 AND 9").collect()} == {1, 5}
    assert [tuple(r) for r in index.range_of(5).collect()] == [(15, 16)]
    assert [tuple(r) for r in index.range_of(4, 3).collect()] == [(11, 12)]
    io.save(index, str(tmp_path / "i"))
    back = io.load(spark, str(tmp_path / "i"))
    want = {tuple(r) for r in queries.metro_numbers(spark).collect()}
    assert {(r.s, r.p, r.o) for r in back.triple_at(back.columns["p"].select("pos")).collect()} == want and back.n == 16
    assert inverse_id(2, 5) == 7 and inverse_id(7, 5) == 2


def test_bits_and_wavelet_against_lists():
    rnd = random.Random(1)
    for _ in range(40):
        n, sigma = rnd.randrange(1, 200), rnd.randrange(1, 12)
        seq = [rnd.randrange(sigma) for _ in range(n)]
        b = bits.Bits(np.array([x & 1 for x in seq]))
        assert [int(b.rank1(i)) for i in range(n + 1)] == [sum(x & 1 for x in seq[:i]) for i in range(n + 1)]
        w = wavelet.build(seq, sigma)
        assert [w.access(i) for i in range(n)] == seq
        for _ in range(10):
            lo, c, x = rnd.randrange(n), rnd.randrange(sigma), rnd.randrange(sigma)
            hi = rnd.randrange(lo, n) + 1
            part = seq[lo:hi]
            assert w.rank(c, hi) == seq[:hi].count(c)
            assert w.distinct(lo, hi) == [(s, seq[:lo].count(s), seq[:hi].count(s)) for s in sorted(set(part))]
            masks = {s: rnd.randrange(8) for s in range(sigma)}
            assert [s for s, *_ in w.distinct_masked(lo, hi, 5, wavelet.label_masks(w.height, masks))] == [s for s in sorted(set(part)) if masks[s] & 5]
            assert w.next_value(lo, hi, x) == min([s for s in part if s >= x], default=None)
            assert w.intersect((0, lo), (lo, hi)) == sorted(set(seq[:lo]) & set(part))


def test_inner_nodes_hold_the_states_of_all_below():
    w = wavelet.build([x - 1 for x in L["s"]], 5)
    seen = wavelet.no_states(w.height, {0, 1, 2, 3, 4})
    # SA alone is visited with a state; its sibling UCh must stay open for it.
    assert w.distinct_unvisited(5, 6, 0b1000, seen) == [(0, 0b1000)]
    assert w.distinct_unvisited(11, 13, 0b1000, seen) == [(1, 0b1000)]
    assert w.distinct_unvisited(5, 6, 0b1010, seen) == [(0, 0b0010)]
    assert w.distinct_unvisited(0, 16, 0, seen) == []
