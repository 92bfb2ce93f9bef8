import random

import numpy as np

from rpqspark.llm import quality


def corpus(n=1500, seed=1):
    rnd = random.Random(seed)
    vocab = ["".join(rnd.choice("abcdefghij") for _ in range(rnd.randrange(2, 9))) for _ in range(400)]
    rows, labels = [], []
    for i in range(n):
        words = [rnd.choice(vocab) for _ in range(rnd.randrange(20, 120))]
        q, t = 1, 0
        if rnd.random() < 0.2:
            q = 0
            words = rnd.choice([[w.upper() + "!!" for w in words], [words[0]] * len(words), [w + "###" for w in words]])
        elif rnd.random() < 0.2:
            t = 1
            for _ in range(4):
                words[rnd.randrange(len(words))] = "zork" + rnd.choice(vocab)
        rows.append((i, " ".join(words), rnd.choice(["en", "de"]), f"s{i % 5}", len(words)))
        labels.append((i, q, t))
    return rows, labels


def test_held_out_accuracy_and_odd_rows(spark):
    rows, labels = corpus()
    known = labels[:1000] + [(1001, None, None), (None, 1, 0)]
    odd = [(9001, None, None, None, None), (9002, "", "xx", "yy", -5), (None, "abc " * 50, "en", "s1", 3)]
    docs = spark.createDataFrame([(*r, "c") for r in rows + odd], "doc_id long, text string, lang string, source string, n_chars long, quality string")
    got = quality.score(docs, spark.createDataFrame(known, "doc_id long, quality int, toxic int")).collect()
    assert len(got) == len(rows) + 3 and all(0 <= r.low_quality <= 1 and 0 <= r.toxic <= 1 for r in got)
    truth = {i: q == 1 and t == 0 for i, q, t in labels}
    held = [r for r in got if r.doc_id in truth and r.doc_id >= 1002]
    assert np.mean([r.keep == truth[r.doc_id] for r in held]) > 0.95
    stay = quality.kept(docs, spark.createDataFrame(known, "doc_id long, quality int, toxic int"))
    assert stay.columns == docs.columns and stay.count() == sum(r.keep for r in got)


def test_no_labels_rejects_nothing(spark):
    docs = spark.createDataFrame([(1, "a b c", "en", "s", 5)], "doc_id long, text string, lang string, source string, n_chars long")
    empty = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert [r.keep for r in quality.score(docs, empty).collect()] == [True]
    assert quality.score(docs.filter("false"), empty).collect() == []


def test_every_unlabelled_document_reaches_the_other_view(spark, monkeypatch):
    """Rows counted as lent, against all rows of which the metadata view of the labelled fit is sure."""
    rows, labels = corpus(n=6000, seed=2)
    rows = [(*r[:3], "bad" if q == 0 else r[3], r[4]) for r, (_, q, _) in zip(rows, labels)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    known = spark.createDataFrame([(i, q, None) for i, q, _ in labels[:600]], "doc_id long, quality int, toxic int")
    seen = []
    summed = quality._summed

    def spy(free, widths, made):
        out = summed(free, widths, made)
        seen.append({k: v[-2] for k, v in out.items()})
        return out

    monkeypatch.setattr(quality, "_summed", spy)
    quality.train(docs, known)
    assert seen[0][0] > 5000


def test_features_pack_and_unpack():
    import pyarrow as pa

    sets = [[], [0], [65535], [5, 131070, 262143], [1, 2, 3], [200000]]
    packed = pa.array(quality._packed(quality.Rows.of(sets)), pa.binary())
    measures = pa.array([np.arange(quality.MEASURES, dtype=float).tobytes()] * len(sets), pa.binary())
    text, _ = quality._unpacked(packed, measures, pa.array([np.array([1, 2, 3, 4], "<u2").tobytes()] * len(sets), pa.binary()))
    assert [x.tolist() for x in np.split(text.slots, text.ends[:-1])] == sets


def test_text_view_equals_a_plain_form():
    rnd = random.Random(6)
    texts = [None, "", " ", "!!! ,", "Ünïcode «wörd» ¿que? a b", "one", "x" * 5000, "La la LA la", "a|b! #c\n\nd\n\n12 3"]
    texts += [" ".join(rnd.choice(["abc", "Abcd.", "(abcde)", "ÄÖÜäöü", "ABC", "日本語テキスト"]) for _ in range(rnd.randrange(40))) for _ in range(30)]

    def one(word):
        data = np.frombuffer(word.encode(), np.uint8)
        return tuple(int(h[0]) & (1 << quality.WORD_BITS) - 1 for h in quality._hash_words(data, np.array([0]), np.array([len(data)])))

    for whole in (quality.text_rows(texts),):
        starts = [0, *whole.ends[:-1].tolist()]
        for t, a, b, d in zip(texts, starts, whole.ends.tolist(), whole.dense):
            words = [w.decode() for w in (t or "").lower().encode().split()]
            bare = [w.strip(quality._STRIP) or w for w in words]
            want = {one(w)[0] for w in bare} | {one(w)[1] for w in bare}
            assert whole.slots[a:b].tolist() == sorted(want)
            assert all(one(w)[1] == one(w[: quality.BEGINNING])[1] for w in bare)
            n = max(1, len(words))
            assert abs(d[0] - sum(x == y for x, y in zip(words, words[1:])) / n) < 1e-12
            assert abs(d[8] - np.log(n) / 8) < 1e-12
    one_by_one = [quality.text_rows([t]) for t in texts]
    assert np.concatenate([r.slots for r in one_by_one]).tolist() == whole.slots.tolist()
    assert quality.text_rows([]).dense.shape == (0, quality.MEASURES)


def plain_lent(past, rows, confident):
    """Labels lent to each head and view, row by row: the first round of which the other view is sure."""
    out = []
    for pairs in past:
        for v in range(2):
            own = []
            for i in range(len(rows[0].ends)):
                label = None
                for pair in pairs:
                    p = 1 / (1 + np.exp(-pair[1 - v].calibrated(rows[1 - v].take(np.array([i])))[0]))
                    if label is None and (p >= confident or p <= 1 - confident):
                        label = float(p >= 0.5)
                own.append(label)
            out.append(own)
    return out


def test_exchange_of_labels_equals_a_plain_form(spark):
    """What executors lend and add up for a round, against one process that goes row by row."""
    from rpqspark.llm import common

    rows, labels = corpus(n=400, seed=5)
    rows = [(*r[:3], "bad" if q == 0 else r[3], r[4]) for r, (_, q, _) in zip(rows, labels)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").repartition(3)
    known = spark.createDataFrame([(i, q, t) for i, q, t in labels[:150]], "doc_id long, quality int, toxic int")
    store = common.Stage(spark, "test").save(quality.features(docs, known), "features")
    t = store.filter("own").toArrow().sort_by("doc_id").combine_chunks()
    views = quality._unpacked(*(t.column(c).combine_chunks() for c in ("slots", "measures", "meta")))
    y = 1.0 - np.array(t.column("quality").to_pylist(), float)
    own = [quality._Labelled(views, y)]
    past = [[own[0].first()]]
    free = store.filter("NOT own").select("slots", "measures", "meta")
    local = free.toArrow().combine_chunks()
    all_rows = quality._unpacked(*(c.combine_chunks() for c in local.columns))
    want = plain_lent(past, all_rows, 0.9)
    got = quality._lent(past, all_rows, 0.9)
    assert [[None if np.isnan(x) else x for x in r] for r in got.tolist()] == want and sum(x is not None for x in want[0]) > 50
    sums = quality._summed(free, {0: 2 * (1 << quality.WORD_BITS) + 2 * quality.MEASURES + 2}, lambda b: (lambda r, l: {0: quality._counts(r[0].take(at), l[0][at], 1 << quality.WORD_BITS) for at in [np.flatnonzero(~np.isnan(l[0]))]})(r := quality._unpacked(*b.columns), quality._lent(past, r, 0.9)))
    at = [i for i, x in enumerate(want[0]) if x is not None]
    seen, bad = np.zeros(1 << quality.WORD_BITS), np.zeros(1 << quality.WORD_BITS)
    for i in at:
        slots = all_rows[0].take(np.array([i])).slots
        seen[slots] += 1
        bad[slots] += want[0][i]
    m = 1 << quality.WORD_BITS
    assert (sums[0][:m] == seen).all() and (sums[0][m : 2 * m] == bad).all()
    assert sums[0][-2] == len(at) and sums[0][-1] == sum(want[0][i] for i in at)


def test_slope_is_the_slope():
    rng = np.random.default_rng(3)
    rows = quality.Rows.of([rng.choice(50, 6, replace=False) for _ in range(40)], rng.standard_normal((40, 3)))
    y = rng.integers(0, 2, 40).astype(float)
    names = np.arange(0, 50, 2)
    point = quality.Point(6, names, np.zeros(3), np.ones(3), rng.standard_normal(len(names) + 4) * 0.1)
    g = point.slope(rows, y)
    for i in range(len(point.at)):
        at = point.at.copy()
        losses = []
        for step in (1e-5, -1e-5):
            point.at = at.copy()
            point.at[i] += step
            losses.append(point.slope(rows, y)[-1])
        point.at = at
        assert abs((losses[0] - losses[1]) / 2e-5 - g[i]) < 1e-4
