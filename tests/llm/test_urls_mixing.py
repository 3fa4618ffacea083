import random
from collections import defaultdict

from pyspark.sql import functions as F

from chaincores.llm import decontaminate, mixing, urls


def fill(sizes, weights, share, most):
    """Water-filling by repetition: deal the rest by weight, stop at the caps."""
    total = share * sum(sizes.values())
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    w = {s: weights[i % len(weights)] for i, s in enumerate(order)}
    target = {}
    open_ = list(order)
    while open_:
        left = total - sum(target.values())
        level = left / sum(w[s] for s in open_)
        full = [s for s in open_ if level * w[s] > most * sizes[s]]
        if not full:
            target |= {s: level * w[s] for s in open_}
            break
        target |= {s: most * sizes[s] for s in full}
        open_ = [s for s in open_ if s not in full]
    return target


def test_targets_and_copies(spark):
    rng = random.Random(2)
    rows = []
    for s, n in (("a", 400), ("b", 30), ("c", 5), ("Z", 900), (None, 60), ("é", 1), ("empty", 3)):
        rows += [(len(rows) + i, " ".join("w" for _ in range(rng.randrange(1, 60))) if s != "empty" else " ", s, 1) for i in range(n)]
    rows += [rows[0], rows[0], (None, "x y", "a", 1), (7, None, "a", 1)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, size int").repartition(4)
    got = mixing.with_copies(df).collect()
    assert len(got) == len(rows)
    sizes = defaultdict(int)
    for _, t, s, _ in rows:
        sizes[s] += len((t or "").split())
    want = fill(sizes, (3, 1, 2), 1.5, 2)
    taken = defaultdict(int)
    for r in got:
        assert abs(r._target - want[r.source]) < 1e-6 and 0 <= r._copies <= 2 and r._source_size == sizes[r.source]
        taken[r.source] += r._size * r._copies
    for s in sizes:
        assert abs(taken[s] - want[s]) <= 120, s
    again = mixing.with_copies(df.repartition(7)).select("doc_id", "_size", "_copies").collect()
    assert sorted(map(str, again)) == sorted(str(r.__class__(doc_id=r.doc_id, _size=r._size, _copies=r._copies)) for r in got)
    assert mixing.mix(df).count() == sum(r._copies for r in got)
    assert mixing.mix(df.limit(0)).count() == 0


def test_urls(spark):
    cases = [("http://A.example.net/en/x?q", "a.example.net", "/en/x", "example.net/en/", "allow"), ("https://x.net/", "x.net", "/", "net/", "block"), ("http://x.net", "x.net", "", None, "allow"), ("//nothing", "", "", None, "allow"), (None, "", "", None, "allow"), ("http://de.example.com/de/a#b", "de.example.com", "/de/a", "example.com/de/", "block"), ("ftp://w.org/fr/?x", "w.org", "/fr/", "org/fr/", "allow"), ("a://b://c/d", "b:", "//c/d", None, "allow"), ("http://notnet/", "notnet", "/", None, "allow"), ("http://É.NET?x", "É.net", "", None, "allow")]
    df = spark.createDataFrame([(i, u, "x") for i, (u, *_) in enumerate(cases)], "page_id long, url string, host string")
    none = spark.createDataFrame([], "page_id long, bad int")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in urls.judge_urls(df, none).collect()}
    assert got == {i: tuple(c[1:]) for i, c in enumerate(cases)}
    pages = [(i, f"http://{'bad' if i % 2 else 'good'}.site{i % 4}.com/") for i in range(400)]
    out = urls.judge_urls(spark.createDataFrame(pages, "page_id long, url string"), spark.createDataFrame([(i, int(i % 2 == 1)) for i in range(0, 400, 3)], "page_id long, bad int"))
    assert {(r.host.split(".")[0], r.verdict) for r in out.collect()} == {("bad", "block"), ("good", "allow")}


def test_hosts_without_labels_inherit(spark):
    labelled = [(i, f"http://h{i % 4}.{'bad' if i % 2 else 'good'}.com/", i % 2) for i in range(800)] + [(800 + i, f"http://h{i % 4}.site{i % 3}.org/", 1) for i in range(400)]
    unseen = ["http://new.bad.com/", "http://new.good.com/", "http://a.other.org/", "http://a.other.com/", "http://a.b.info/"]
    pages = [(i, u) for i, u, _ in labelled] + [(5000 + i, u) for i, u in enumerate(unseen)]
    out = urls.judge_urls(spark.createDataFrame(pages, "page_id long, url string"), spark.createDataFrame([(i, b) for i, _, b in labelled], "page_id long, bad int"), rules=())
    got = {r.page_id: r for r in out.collect()}
    assert len(got) == len(pages) and all(got[5000 + i].bad_bound is not None for i in range(5))
    assert [got[5000 + i].verdict for i in range(3)] == ["block", "allow", "block"]
    assert got[5001].bad_bound < got[5003].bad_bound < got[5002].bad_bound and got[5001].bad_bound < got[5004].bad_bound < got[5000].bad_bound


def brute_decontaminate(docs, bench, window=10):
    import re

    words = lambda t: re.findall(r"[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in t or ""))
    grams = defaultdict(set)
    for item, t in bench:
        w = words(t)
        m = min(window, len(w))
        for i in range(len(w) - m + 1 if w else 0):
            grams[tuple(w[i : i + m])].add(str(item))
    out = []
    for d, t in docs:
        w, hit, items = words(t), set(), set()
        for m in {len(g) for g in grams}:
            for i in range(len(w) - m + 1):
                if (g := tuple(w[i : i + m])) in grams:
                    hit |= set(range(i, i + m))
                    items |= grams[g]
        out.append((d, len(w), len(hit), len(items)))
    return out


def test_decontaminate_against_brute_force(spark, monkeypatch):
    rng = random.Random(6)
    vocab = ["Ab", "b1", "é", "dd", "x", "Y"]
    bench = [(i, " ".join(rng.choice(vocab) for _ in range(n))) for i, n in enumerate([25, 12, 10, 9, 3, 3, 0, 14])] + [(9, None), (3, "b1, x. dd")]
    docs = [(i, "; ".join(rng.choice(vocab) for _ in range(rng.randrange(40)))) for i in range(80)]
    docs += [(100 + i, "q " + t + " q" if t else t) for i, t in bench] + [(5, docs[5][1]), (5, "q"), (None, bench[0][1])]
    want = sorted(brute_decontaminate(docs, bench), key=str)
    d = spark.createDataFrame([(i, t, "x") for i, t in docs], "doc_id long, text string, pos string")
    b = spark.createDataFrame(bench, "item_id long, text string")
    for limit in (decontaminate.BROADCAST_WINDOWS, 0):
        monkeypatch.setattr(decontaminate, "BROADCAST_WINDOWS", limit)
        got = sorted((tuple(r)[:4] for r in decontaminate.report(d, b).collect()), key=str)
        assert got == want
    kept = decontaminate.drop_contaminated(d, b, min_words=1)
    assert kept.columns == d.columns and kept.count() == sum(not h for _, _, h, _ in want)
    assert decontaminate.report(d, b.limit(0)).agg(F.sum("n_hit")).first()[0] == 0


def test_op8_equals_its_sql_on_hosts_without_labels(spark, tmp_path):
    import duckdb

    from chaincores.llm import queries

    urls_ = [f"http://h{i % 4}.{'bad' if i % 2 else 'good'}.com/" for i in range(400)] + ["http://new.bad.com/", "http://new.good.com/x", "http://a.b.info/", None, "nothing"]
    spark.createDataFrame(list(enumerate(urls_)), "page_id long, url string").write.parquet(f"{tmp_path}/pages.parquet")
    spark.createDataFrame([(i, 1 - i % 2, 0) for i in range(400)] + [(7, None, 0), (None, 0, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    c = duckdb.connect()
    for t in ("pages", "labels"):
        c.execute(f"create view {t} as select * from '{tmp_path}/{t}.parquet/*.parquet'")
    want = c.execute(queries.ORACLES["op8_url_reputation"]).fetchall()
    assert sorted(map(str, map(tuple, queries.op8_url_reputation(spark, str(tmp_path)).collect()))) == sorted(map(str, want))
