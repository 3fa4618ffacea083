import hashlib
import random
from collections import Counter

import numpy as np

from chaincores.llm import induced, suffixes


def check_order(b, limit, memory):
    pos, lcp = (np.concatenate(x).tolist() for x in zip(*induced.sorted_suffixes(induced.Symbols(np.frombuffer(b, np.uint8), 256), limit, memory), strict=True))
    assert sorted(pos) == list(range(len(b)))
    keys = [b[p : p + limit] for p in pos]
    assert keys == sorted(keys, reverse=True)
    for p, q, n in zip(pos, pos[1:], lcp[1:]):
        assert n == next((i for i in range(limit) if max(p, q) + i >= len(b) or b[p + i] != b[q + i]), limit)


def test_order_and_prefixes_against_brute_force():
    rng = random.Random(1)
    for _ in range(600):
        b = bytes(rng.choice(rng.choice([b"ab", b"abc", b"a", b"a\x00b", bytes(range(97, 117))])) for _ in range(rng.randrange(1, 90)))
        b += b[: rng.randrange(len(b)) + 1] + bytes([induced.END])
        check_order(b, rng.choice([2, 4, 8, 50]), rng.choice([1, 64, 1 << 20]))


def test_recursion_with_memory_far_below_the_text(monkeypatch):
    """Words of few letters repeat at all lengths, so several levels are needed; queues and arrays lie on disk."""
    levels = []
    run = induced.sort_stars
    monkeypatch.setattr(induced, "sort_stars", lambda s, stars, *more: (levels.append((s.size, len(stars))), run(s, stars, *more))[1])
    monkeypatch.setattr(induced, "BATCH", 1000)
    rng = random.Random(3)
    words = [bytes(rng.choice(b"abcd") for _ in range(rng.randrange(2, 9))) for _ in range(60)]
    text = b" ".join(rng.choice(words) for _ in range(6000))
    text = text + b"|" + text[5000:9000] + bytes([induced.END])
    check_order(text, 100, 4096)
    assert len(levels) >= 4 and all(x[1] * 2 <= len(text) for x in levels) and max(size for size, _ in levels) > 256


def brute(texts, length):
    n = Counter(t[i : i + length] for t in texts for i in range(len(t) - length + 1))
    out = []
    for t in texts:
        gone = np.zeros(len(t), bool)
        for i in range(len(t) - length + 1):
            if n[t[i : i + length]] > 1:
                gone[i : i + length] = True
        runs = int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum())
        kept = bytes(x for x, g in zip(t, gone, strict=True) if not g)
        out.append((len(t), int(gone.sum()), runs, hashlib.sha256(kept).hexdigest()))
    return out


def test_report_against_brute_force(spark, monkeypatch):
    monkeypatch.setattr(suffixes, "PIECE", 700)
    rng = random.Random(4)
    word = lambda: "".join(rng.choice("abcdé") for _ in range(rng.randrange(1, 6)))
    passage = [" ".join(word() for _ in range(120)) for _ in range(3)]
    texts = []
    for _ in range(60):
        t = " ".join(word() for _ in range(rng.randrange(0, 300)))
        for _ in range(rng.randrange(3)):
            p = rng.choice(passage)
            a = rng.randrange(len(p) // 3)
            t = t[: (k := rng.randrange(len(t) + 1))] + p[a : a + rng.randrange(300, 500)] + t[k:]
        texts.append(t)
    texts += [texts[0]] * 3 + [None, "", "a" * 1500, "a" * 400, "b" * 401, "c" * 399]
    rows = [(i, t, 0) for i, t in enumerate(texts)] + [(5, texts[5], 0), (None, texts[6], 0)]
    df = spark.createDataFrame(rows, "doc_id long, text string, n_bytes int").repartition(5)
    got = sorted((tuple(r) for r in suffixes.report(df).collect()), key=str)
    want = sorted(((i, *x) for (i, *_), x in zip(rows, brute([(t or "").encode() for _, t, _ in rows], 400), strict=True)), key=str)
    assert got == want
    assert suffixes.report(df.limit(0)).count() == 0


def test_cut_keeps_whole_characters(spark):
    p = "é" * 50 + "".join(chr(0x4E00 + i) for i in range(60))
    df = spark.createDataFrame([(1, "x" + p + "y", 9), (2, "zz" + p, 9), (3, None, None), (4, "short", 5)], "doc_id long, text string, n_chars long")
    got = {r.doc_id: (r.text, r.n_chars) for r in suffixes.cut_repeats(df, 100).collect()}
    assert got == {1: ("xy", 2), 2: ("zz", 2), 3: (None, None), 4: ("short", 5)}
