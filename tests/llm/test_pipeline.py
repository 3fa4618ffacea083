import random

import numpy as np
import pytest

import corpus_pipeline
from chaincores.llm import neardup


def shingles(t):
    w = (t or "").lower().split()
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} or ({tuple(w)} if w else set())


def brute_keep(rows):
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    sets = [shingles(t) for _, t in rows]
    for i in range(len(rows)):
        for j in range(i):
            a, b = sets[i], sets[j]
            if (not a and not b) or (a and b and len(a & b) >= 0.8 * len(a | b)):
                root[max(find(i), find(j))] = min(find(i), find(j))
    groups = {}
    for i, (d, _) in enumerate(rows):
        groups.setdefault(find(i), []).append(d)
    return sorted(min(g, key=lambda d: (d is None, d or 0)) for g in groups.values() if any(d is not None for d in g)), sum(all(d is None for d in g) for g in groups.values())


def test_near_duplicates_against_brute_force(spark):
    rng = random.Random(8)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(4))
    rows = []
    for _ in range(40):
        base = [word() for _ in range(rng.randrange(30, 120))]
        for _ in range(rng.randrange(1, 6)):
            w = list(base)
            for _ in range(rng.choice([0, 0, 1, 1, 2, 3])):
                w[rng.randrange(len(w))] = word()
            rows.append((len(rows), " ".join(w)))
    big = [word() for _ in range(150)]
    for _ in range(60):
        w = list(big)
        w[rng.randrange(150)] = word()
        rows.append((len(rows), " ".join(w)))
    rows += [(900, None), (901, " "), (902, "a b"), (903, "A  b"), (3, rows[3][1]), (None, "solo text alone here now yes")]
    got = [r.doc_id for r in neardup.keep_one(spark.createDataFrame([(i, t, 0) for i, t in rows], "doc_id long, text string, _x int")).collect()]
    want, nulls = brute_keep(rows)
    assert sorted(d for d in got if d is not None) == want and got.count(None) == nulls
    assert neardup.keep_one(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_short_texts_meet_surely():
    rng = random.Random(2)
    for n in range(1, 41):
        for _ in range(40):
            a = np.array([rng.getrandbits(64) for _ in range(n)], np.uint64)
            lost = rng.randrange(n - -(-8 * n // 10) + 1)
            more = rng.randrange(int((n - lost) / 0.8 - n + 1e-9) + 1) if (n - lost) / 0.8 >= n else 0
            b = np.concatenate([a[lost:], np.array([rng.getrandbits(64) for _ in range(more)], np.uint64)])
            if (n - lost) >= 0.8 * (n + more):
                assert set(neardup.keys(np.unique(a)).tolist()) & set(neardup.keys(np.unique(b)).tolist())


@pytest.mark.parametrize("parts", [(1, 1), (3, 2)])
def test_one_large_group_loses_no_link(parts):
    """Copies edited at random around the limit, in one bucket: components as by all pairs, with fewer links than sets."""
    rng = random.Random(5)
    base = [rng.getrandbits(63) for _ in range(100)]
    sets = []
    for _ in range(300):
        s = set(base)
        for x in rng.sample(base, rng.choice([0, 2, 5, 9, 10, 11, 12, 20])):
            s.discard(x)
            s.add(rng.getrandbits(63))
        sets.append(np.array(sorted(s), np.int64))
    sets += [np.zeros(0, np.int64)] * 2 + [np.array(sorted(rng.getrandbits(63) for _ in range(60)), np.int64)]

    def joined(pairs):
        root = list(range(len(sets)))

        def find(i):
            while root[i] != i:
                i = root[i]
            return i

        for i, j in pairs:
            root[find(i)] = find(j)
        return [find(i) for i in range(len(sets))]

    want = joined((i, j) for i in range(len(sets)) for j in range(i) if (c := len(np.intersect1d(sets[i], sets[j]))) >= 0.8 * (len(sets[i]) + len(sets[j]) - c))
    out = [i for i in range(len(sets)) if i not in (0, 1)]  # two that are known to be of the largest component, if they are
    pairs = []
    if want[0] != want[1]:
        out.append(1)
    for x in range(parts[0]):
        for y in range(parts[1]):
            at = [(i, 0) for i in out if i % parts[0] == x] + [(i, 2 if i in out else 1) for i in range(len(sets)) if i % parts[1] == y and not (parts == (1, 1) and i in out)]
            label = np.array([0 if i not in out else i + 1 for i, _ in at])
            got = neardup.link_bucket([sets[i] for i, _ in at], label, np.array([s for _, s in at]), 0.8)
            pairs += [(at[i][0], at[j][0]) for i, j in got]
    got = joined(pairs + [(0, i) for i in range(len(sets)) if i not in out])
    assert len(set(zip(want, got, strict=True))) == len(set(want)) == len(set(got))
    assert len(pairs) <= len(sets) * parts[0] * parts[1]


@pytest.mark.parametrize("held", [4_000_000, 3_000])
def test_large_group_in_spark(spark, monkeypatch, held):
    monkeypatch.setattr(neardup, "HELD", held)
    monkeypatch.setattr(neardup, "ASKED", held // 2)
    rng = random.Random(11)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(4))
    base = [word() for _ in range(120)]
    rows = []
    for i in range(200):
        w = list(base)
        for _ in range(rng.choice([0, 1, 2, 2, 3, 3, 4])):
            w[rng.randrange(120)] = word()
        rows.append((i, " ".join(w)))
    got = sorted(r.doc_id for r in neardup.keep_one(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert got == brute_keep(rows)[0]


def test_stages_keep_the_columns(spark):
    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns
    assert corpus_pipeline.run(spark, sf).count() > 0


def test_stages_on_empty_and_odd_tables(spark, tmp_path):
    """Empty tables, columns of clashing names, nulls in every column, repeated rows and one very long text."""
    from chaincores.llm.common import table

    sf = "/root/testdata/sf0.001"
    for name in ("documents", "labels", "benchmark"):
        table(spark, sf, name).limit(0).write.parquet(f"{tmp_path}/{name}.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
    docs = table(spark, sf, "documents").limit(12).selectExpr("*", "1 as node", "'x' as bucket", "2 as key", "3 as h", "4 as size", "5 as comp")
    odd = spark.createDataFrame([(None, None, None, None, None), (901, " ", "en", None, 1), (901, " ", "en", None, 1), (902, "long words go here " * 60_000, None, "s", 1)], "doc_id long, text string, lang string, source string, n_chars int")
    odd = docs.unionByName(odd, allowMissingColumns=True).select(*docs.columns)
    for _, stage in corpus_pipeline.STAGES:
        out = stage(spark, odd, sf)
        assert out.columns == odd.columns and out.count() >= 0


def test_whole_fingerprints_meet_by_the_popcount_grid(spark):
    import hashlib
    import random

    from chaincores.llm import neardup

    rng = random.Random(12)
    base = [f"w{rng.randrange(10**6)}" for _ in range(900)]
    texts, far = {}, " ".join(f"v{rng.randrange(10**6)}" for _ in range(900))
    fp = lambda t: neardup.whole_fingerprint(neardup.shingle_set(t.encode())) & (2**64 - 1)
    for i in range(60):
        t = " ".join(["new" if j == i * 15 else w for j, w in enumerate(base)])
        texts.setdefault((fp(" ".join(base)) ^ fp(t)).bit_count(), t)
    near = {d: t for d, t in texts.items() if d <= 3}
    assert max(near) >= 1
    docs = spark.createDataFrame([(0, " ".join(base)), (1, far), (2, None), *((3 + d, t) for d, t in near.items())], "doc_id long, text string")
    got = {bytes(r.node): r.bucket for r in neardup.grid_buckets(neardup.buckets(docs).where("bucket is null")).collect()}
    node = lambda t: hashlib.md5((t or "").encode()).digest()
    assert {got[node(t)] for t in near.values()} == {got[node(" ".join(base))]} and len({got[node(t)] for t in (" ".join(base), far, None)}) == 3
    assert {r.doc_id for r in neardup.keep_one(docs).collect()} == {0, 1, 2}
