import random

import numpy as np
import pyarrow as pa

from chaincores.llm import gru, quality, toxicity
from chaincores.llm.common import word_codes


def test_gradients_match_differences():
    rng = np.random.default_rng(0)
    net = gru.Network(3)
    net.p = {k: v.astype(np.float64) for k, v in net.p.items()}
    x = rng.normal(size=(9, gru.WORD + gru.CHAR))
    lengths = np.array([4, 1, 7, 0])
    index = np.where(np.arange(7)[None] < lengths[:, None], rng.integers(0, 9, (4, 7)), 9)
    w = rng.normal(size=4)

    def loss():
        return float((net.forward(*net.gates(x), index, lengths) * w).sum())

    _, memo = net.forward(*net.gates(x), index, lengths, keep=True)
    grad, _, _ = net.backward(memo, w)
    for k in ("o", "b", "v", "A", "a", "Uf", "Ub"):
        flat = net.p[k].ravel()
        for i in rng.integers(0, flat.size, 3):
            old = flat[i]
            flat[i] = old + 1e-2
            up = loss()
            flat[i] = old - 1e-2
            down = loss()
            flat[i] = old
            assert abs((up - down) / 2e-2 - np.asarray(grad[k]).ravel()[i]) < 2e-3, k


def test_windows_cover_every_word():
    for n in [0, 1, 31, 32, 33, 48, 49, 200]:
        owner, first, lengths = gru.windows(np.array([5, n]))
        own = owner == 1
        seen = {i for s, k in zip(first[own] - 5, lengths[own], strict=True) for i in range(s, s + k)}
        assert seen == set(range(n)) and own.any()


def corpus(n, seed=0):
    rng = random.Random(seed)
    base = ["".join(rng.choice("abcdefgh") for _ in range(rng.randrange(2, 8))) for _ in range(300)]
    rows, labels = [], []
    for i in range(n):
        words = [rng.choice(base) for _ in range(rng.randrange(20, 150))]
        toxic, junk = rng.random() < 0.3, rng.random() < 0.3
        if toxic:
            words[rng.randrange(len(words))] = "vil" + rng.choice(["lo", "xe", "rum", "da"])
            words[rng.randrange(len(words))] = "vil" + rng.choice(["ka", "xo", "rim", "du"])
        if junk:
            words = [w + "%%%" for w in words]
        rows.append((i, " ".join(words)))
        labels.append((i, int(not junk), int(toxic)))
    return rows, labels


def test_toxicity_on_held_out_rows(spark):
    rows, labels = corpus(900)
    docs = spark.createDataFrame([*rows, (901, None), (902, ""), (None, "x"), (3, rows[3][1])], "doc_id long, text string").selectExpr("*", "1 as score")
    lab = spark.createDataFrame([*labels, (5, None, None)], "doc_id long, quality int, toxic int")
    got = toxicity.scores(docs, *toxicity.fit(docs, lab)).collect()
    assert len(got) == 904 and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) for r in got)
    truth = {i: t for i, _, t in labels}
    held = [(r.predicted, truth[r.doc_id]) for r in got if r.held_out and r.doc_id in truth]
    assert len(held) > 100 and np.mean([a == b for a, b in held]) > 0.85
    assert toxicity.scores(docs.limit(0), *toxicity.fit(docs, lab.limit(0))).count() == 0


def test_quality_keeps_good_rows(spark):
    rows, labels = corpus(600, 2)
    docs = spark.createDataFrame([*rows, (901, None), (902, "")], "doc_id long, text string").selectExpr("*", "1 as _other")
    lab = spark.createDataFrame([(i, q) for i, q, _ in labels] + [(None, 1), (1, None)], "doc_id long, quality int")
    kept = {r.doc_id for r in quality.select(docs, lab).collect()}
    right = [(i in kept) == bool(q) for i, q, _ in labels]
    assert np.mean(right) > 0.97
    assert quality.select(docs, lab.limit(0)).count() == 602  # without ratings nothing is rejected


def test_graded_thresholds_are_ordered():
    rng = np.random.default_rng(1)
    y = rng.integers(0, 4, 400).astype(float)
    rows = [(np.array([int(g), 10]), np.array([0.5, 0.5])) for g in y]
    m = quality.fit_rows(y, rows)
    assert (np.diff(m.thresholds) >= 0).all()
    s = np.array([quality.SCALE * (v * m.weights[i]).sum() for i, v in rows])
    e = m.expected(m.tails(s))
    assert [e[y == g].mean() for g in range(4)] == sorted(e[y == g].mean() for g in range(4))
    assert abs(e - y).mean() < 0.3


def test_word_codes():
    codes, words, counts = word_codes(pa.array([" A  b\tA\n", None, "", "É a"]))
    assert counts.tolist() == [3, 0, 0, 2]
    assert [words[int(c)].as_py() for c in codes] == ["a", "b", "a", "É", "a"]


def test_quality_learns_from_every_part_of_long_texts(spark, monkeypatch):
    from chaincores.llm import quality

    # the word that tells lies in the 25th of forty parts only, between what evenly spaced pieces would show
    parts = [" ".join(f"w{i % 7}" for i in range(700)) for _ in range(40)]
    long_ = lambda i: " ".join([*parts[:25], f"{'good' if i % 2 else 'poor'} " * 30, *parts[25:]])
    docs = spark.createDataFrame([(i, long_(i)) for i in range(60)] + [(60, None), (61, "")], "doc_id long, text string").repartition(3)
    labels = spark.createDataFrame([(i, i % 2) for i in range(62)], "doc_id long, quality int")
    whole = quality.fit(docs, labels)
    w = {x: whole.weights[quality.word_features(x)[0]] for x in ("good", "poor")}
    assert w["good"] > 0 > w["poor"]
    monkeypatch.setattr(quality, "PIECE", 40)
    pieces = quality.fit(docs, labels)
    assert np.allclose(whole.weights, pieces.weights, atol=1e-6) and np.allclose(whole.thresholds, pieces.thresholds, atol=1e-6)
    assert quality.fit(docs, labels.limit(0)).weights.any() == False  # noqa: E712
