import random

import numpy as np
import pytest
import xxhash

from chaincores.llm import queries, simhash, tokens
from chaincores.llm.queries import tokenizer_file

MODEL = tokenizer_file("piece_bpe_32k.model")
TEXTS = ["", " ", "  a", "a  b ", "a\nb", "\n", "\n\n x", "a\tb", "<s> x </s>", "▁a ▁", "a b", "é é", "😀 x\r\n;\r y", "a\x00b", "word " * 500, "x" * 3000, "\n" * 50, "Straße ñandú  où\n  indented code(){\r\n}"]


def direct(texts):
    import sentencepiece

    return [len(x) for x in sentencepiece.SentencePieceProcessor(model_file=MODEL).encode(list(texts))]


def test_transducer_equals_library(monkeypatch):
    rng = random.Random(1)
    texts = TEXTS + ["".join(rng.choice(["a", "the", " ", "  ", "\n", "é", "▁", "\r", ";", "字", "\t", "in"]) for _ in range(rng.randrange(40))) for _ in range(1500)]
    t = tokens.Transducer(MODEL)
    raw, want = [x.encode() for x in texts], direct(texts)
    assert t.count_many(raw).tolist() == want
    monkeypatch.setattr(tokens, "HEAD", 4)
    for size in (1, 3, 7, 50):  # chunk maps compose wherever the cut falls
        assert [t.count(x, size) for x in raw] == want
    monkeypatch.setattr(tokens, "STATES", 10)
    assert t.count_many(raw).tolist() == want  # started anew


def test_prefix_scan_counts_every_prefix(monkeypatch):
    monkeypatch.setattr(tokens, "HEAD", 3)
    t = tokens.Transducer(MODEL)
    for text in ["the cat sat on the mat " * 9, "x" * 200, "aaaaéa" * 30]:
        chunks = list(tokens.pieces(text.encode(), 17))
        got = [t.follow(t.keys[0], m)[1] for m in t.scan([t.map(c) for c in chunks])]
        assert got == [t.run("".join(chunks[: i + 1]))[1] for i in range(len(chunks))]
        assert got[-1] == direct([text])[0]


def test_long_texts_are_dealt_out(spark):
    rows = [(1, "the cat\nsat " * 700), (1, "the cat\nsat " * 700), (2, "z" * 5000), (3, "short"), (None, "é字 " * 900), (4, None)]
    got = tokens.token_counts(spark.createDataFrame(rows, "doc_id long, text string"), MODEL, long=1000, chunk=300).collect()
    assert sorted(((r.doc_id, r.n_bytes, r.n_tokens) for r in got), key=str) == sorted(((d, len((x or "").encode()), direct([x or ""])[0]) for d, x in rows), key=str)


def test_query_equals_library_on_a_table(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text").collect()
    got = {r.doc_id: r.n_tokens for r in queries.op6_token_counts(spark, "/root/testdata/sf0.001").collect()}
    assert got == dict(zip([r.doc_id for r in docs], direct([r.text or "" for r in docs]), strict=True))


def test_token_counts_rows(spark):
    rows = [(1, None), (2, ""), (2, "a b"), (2, "a b"), (None, "x" * 9000)]
    got = tokens.token_counts(spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as n_tokens"), MODEL).collect()
    assert [(r.doc_id, r.n_bytes) for r in got] == [(1, 0), (2, 0), (2, 3), (2, 3), (None, 9000)]
    assert [r.n_tokens for r in got] == direct([x or "" for _, x in rows])
    assert tokens.token_counts(spark.createDataFrame([], "doc_id long, text string"), MODEL).count() == 0


def brute_fp(text, k):
    w = text.encode().lower().split()
    if not w:
        return 0
    sh = [b" ".join(w[i : i + k]) for i in range(len(w) - k + 1)] or [b" ".join(w)]
    hs = [xxhash.xxh64_intdigest(s, 42) for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def test_fingerprint():
    for t in ["", " \n", "One", "a b", "a b c", "A b C d e", "É ö x y z É ö x", "the cat sat on the mat " * 20]:
        assert simhash.fingerprint(t.encode(), 3) == brute_fp(t, 3)


def brute_components(fps):
    root = list(range(len(fps)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(fps)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= 3:
                root[find(i)] = find(j)
    return [find(i) for i in range(len(fps))]


@pytest.mark.parametrize("heavy", [20_000, 40])
def test_links_lose_nothing(spark, monkeypatch, heavy):
    monkeypatch.setattr(simhash, "HEAVY", heavy)
    rng = random.Random(3)
    fps = {0}
    for _ in range(60):
        x = rng.getrandbits(64)
        for _ in range(8):
            fps.add(x)
            for b in rng.sample(range(64), rng.choice([1, 2, 3, 3, 4, 5])):
                x ^= 1 << b
    base = rng.getrandbits(64)
    fps |= {base ^ (1 << i) for i in range(64)}  # a dense group
    fps = sorted(fps)
    want = brute_components(fps)
    signed = np.array(fps, np.uint64).view(np.int64).tolist()
    rows = simhash.links(spark.createDataFrame([(x,) for x in signed], "fp long")).collect()
    root = {x: x for x in signed}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for r in rows:
        assert r.a != r.b
        root[find(r.a)] = find(r.b)
    got = [find(x) for x in signed]
    assert len(set(zip(want, got, strict=True))) == len(set(want)) == len(set(got))


def test_near_components_edge_cases(spark):
    rows = [(5, None), (7, "  "), (3, "a b c d"), (9, "a b c d"), (9, "a b c d"), (None, "zz yy xx")]
    got = sorted(((r.doc_id, r.component_id) for r in simhash.near_components(spark.createDataFrame(rows, "doc_id long, text string")).collect()), key=str)
    assert got == sorted([(5, 5), (7, 5), (3, 3), (9, 3), (9, 3), (None, None)], key=str)
    assert simhash.near_components(spark.createDataFrame([], "doc_id long, text string")).count() == 0
