"""Queries against their SQL on the smallest tables, and brute force where SQL has none."""

import math
import os
import random

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from chaincores import queries as q
from chaincores.operators import baselines as B
from chaincores.operators import cores as C
from chaincores.operators import graph as G
from chaincores.operators import linkage as L
from chaincores.operators.components import components
from chaincores.plans import robust
from chaincores.plans.cluster import Settings

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SOME = ["p1_listings", "learned_weights", "name_classes_similar_80", "prune_subcliques", "simplified_index", "components_p1", "borders_k2", "screen_round_1", "sim_dom", "silhouette", "tfidf_assign", "vote_assign_round", "prf_connected", "top5_groups", "join_as_of", "window_range", "stream_sessions", "stream_clique_growth", "candidate_pairs", "stream_late_rows", "stream_assign"]


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return c


def plain(v):
    return round(v, 6) if isinstance(v, float) else str(v) if not isinstance(v, (int, str, type(None))) else v


@pytest.mark.parametrize("name", SOME)
def test_equals_sql(spark, duck, name):
    df = __spark_entry__.queries()[name](spark, SF)
    columns = sorted(df.columns)
    got = sorted(repr(tuple(plain(r[c]) for c in columns)) for r in df.collect())
    cur = duck.execute(__spark_entry__.oracle_sql()[name])
    at = [[d[0] for d in cur.description].index(c) for c in columns]
    assert got == sorted(repr(tuple(plain(r[i]) for i in at)) for r in cur.fetchall())


@pytest.mark.parametrize("local", [0, 10_000])
def test_components_brute_force(spark, local):
    rng = random.Random(3)
    edges = [(rng.randrange(200), rng.randrange(200)) for _ in range(120)] + [(i, i + 1) for i in range(300, 340)] + [(500, 500), (None, 3)]
    got = {r.node: r.comp for r in components(spark.createDataFrame(edges, "a long, b long"), local=local).collect()}
    want = {}
    for p in robust.pieces({x for e in edges if None not in e for x in e}, [frozenset(e) for e in edges if None not in e]):
        want |= dict.fromkeys(p, min(p))
    assert got == want


def test_distributed_screening_equals_local(spark):
    """Components beyond the limit are screened as DataFrames: unions, borders and components, round by round."""
    i = G.graph(q.listings(spark, SF, "p1"))
    rows = i.count()
    for k in (1, 2):
        want = {tuple(x) for x in C.find_cores(i, k, "screen_only", local_limit=rows * 10).collect()}
        got = {tuple(x) for x in C.find_cores(i, k, "screen_only", local_limit=4).collect()}
        assert want and got == want


def test_edge_star_against_brute_force(spark):
    rng = random.Random(6)
    names = [(i, "n", f"p{rng.randrange(12)}", f"u{rng.randrange(12)}", None, rng.choice("xy"), rng.choice("st"), 0) for i in range(60)]
    r = spark.createDataFrame(names, "rid long, name string, phone string, url string, url2 string, state string, category string, gold long")
    edges = sorted(((e.sim, e.r1, e.r2) for e in B.record_pairs(r).where("sim > 0.8").collect()), key=lambda e: (-e[0], e[1], e[2]))
    for merge in (False, True):
        role, of, joined = {}, {}, []
        for _, a, b in edges:
            for x, y in ((a, b), (b, a)):
                if x not in role and y not in role:
                    role[x], of[x], role[y], of[y] = "centre", x, "member", x
                elif role.get(x) == "centre" and y not in role:
                    role[y], of[y] = "member", x
            if merge and of.get(a) != of.get(b) and "centre" in (role.get(a), role.get(b)) and a in of and b in of:
                joined.append((of[a], of[b]))
        of |= {n[0]: n[0] for n in names if n[0] not in of}
        root = {}
        for p in robust.pieces(set(of.values()), [frozenset(x) for x in joined]):
            root |= {c: tuple(sorted(n for n in of if of[n] in p)) for c in p}
        want = {n: root[c][0] for n, c in of.items()}
        assert {x.rid: x.group_id for x in B.edge_star(r, merge=merge).collect()} == want


def test_votes_reach_their_fixpoint(spark):
    """A chain of features: each round gives the next records enough members to stand for."""
    rows = [(i, "a", f"p{i // 6}", f"u{(i + 3) // 6}", None, None, None, 0) for i in range(48)]
    r = spark.createDataFrame(rows, "rid long, name string, phone string, url string, url2 string, state string, category string, gold long")
    r = r.withColumn("name", r.rid.cast("string"))
    cores = spark.createDataFrame([(i, 0) for i in range(6)], "rid long, core long")
    got = {x.rid: x.group_id for x in B.vote_assign(r, cores, 3).collect()}
    assert set(got.values()) == {0}


def test_keys(spark):
    from chaincores.operators import keys as K

    df = spark.createDataFrame([(1, "412-555", "me@Lab.org", "1 oak road"), (2, "41", "none", "2 oak road"), (3, None, None, None), (4, "", "x@y@z.org", "elm lane")], "rid long, phone string, url string, url2 string")
    got = {r.rid: (r.phone, r.url, r.url2) for r in K.dominant_keys(df, {"phone": K.prefix(3), "url": K.email_server}, {"url2": 0.9}).collect()}
    assert got == {1: ("412", "lab.org", "1 oak road"), 2: ("41", None, "1 oak road"), 3: (None, None, None), 4: (None, "z.org", "elm lane")}
    urls = spark.createDataFrame([("https://www.Oak.com/x?y",), ("oak.com:80",), ("ftp://a.b#c",), ("",), (None,)], "u string")
    assert [r.d for r in urls.select(K.url_domain(urls.u).alias("d")).collect()] == ["oak.com", "oak.com", "a.b", None, None]


def test_components_beyond_the_limit(spark):
    k33 = [(100 + x, f"{i}-{j}") for i in range(3) for j in range(3, 6) for x in (i, j)]
    chain = [(n, f"c{n // 2}") for n in range(200, 212)] + [(n, f"d{n // 2}") for n in range(201, 211, 2)] + [(n + 1, f"d{n // 2}") for n in range(201, 211, 2)]
    i = spark.createDataFrame([(n, "hot") for n in range(50)] + k33 + chain, "rid long, clique string")
    cores = lambda k, limit: {tuple(r) for r in C.find_cores(i, k, local_limit=limit).collect()}
    assert cores(0, 1) == {(n, 0) for n in range(50)} | {(100 + n, 100) for n in range(6)} | {(n, 200) for n in range(200, 212)}
    assert cores(2, 0) == cores(2, 1000) >= {(n, 0) for n in range(50)} | {(100 + n, 100) for n in range(6)}


def test_worked_example_groups(spark):
    rows = [(i, "oak", "808" if i <= 5 else str(95 + i), "oak" if i >= 3 else None) for i in range(1, 8)]
    rows += [(11, "corn", None, "corn"), (12, "corn", "900", "corn"), (13, "corn", "900", "corn"), (14, "corn", "900", None), (15, "corn", "900", None), (16, "corn", "701", "south"), (17, "corn", "702", "south"), (18, "corn", "703", "south"), (19, "corn", "704", None), (20, "corn", None, "north")]
    df = spark.createDataFrame([(*r, "south" if r[0] == 13 else None, "XX", "c") for r in rows], "rid long, name string, phone string, url string, url2 string, state string, category string")
    got = {r.rid: r.group_id for r in L.two_stage(df, k=1).collect()}
    assert len({got[i] for i in range(1, 8)}) == 1
    assert got[14] == got[15] == got[12] and got[16] == got[17] == got[18] != got[14]
    assert got[19] == 19 and got[20] == 20


@pytest.mark.parametrize("name", ["jaro_winkler_names_80", "jaro_winkler_parts_80"])
def test_all_similar_pairs(spark, duck, name):
    got = sorted(repr((r.a, r.b, plain(r.sim))) for r in __spark_entry__.queries()[name](spark, SF).collect())
    assert got == sorted(repr((a, b, plain(s))) for a, b, s in duck.execute(__spark_entry__.oracle_sql()[name]).fetchall())
    print(name, len(got), "pairs, other first three letters:", sum(eval(x)[0][:3] != eval(x)[1][:3] for x in got))


def test_learned_weights_come_from_labels(spark):
    rows = [(1, "abcd", "5", 1), (2, "abcd", "5", 1), (3, "abcd", "6", 2), (4, "abcde", "7", 3)]
    df = spark.createDataFrame([(i, n, p, None, g) for i, n, p, g in rows], "rid long, name string, phone string, url string, gold long")
    w = L.weights_of(L.learn_weights(df, q.gold(df), block_threshold=0.8))
    # names: of 6 pairs 3 agree, 1 of them in one group; distinct values have one pair more for and against
    assert w.com == (2 / 5, 4 / 5) and w.com_distinct == (1 / 2, 4 / 5)
    assert w.dom_distinct == (2 / 3, 6 / 7) and w.dom == w.dom_distinct


def test_similar_pairs_differ_in_first_letters(spark):
    df = spark.createDataFrame([("oak tools store",), ("eak tools store",), ("corn house",)], "name string")
    assert [(r.a, r.b) for r in G.similar_pairs(df, 0.8).collect()] == [("eak tools store", "oak tools store")]


@pytest.mark.parametrize("view", ["p3_all", "p4_all", "p4p_all", "p5_all"])
def test_whole_views(spark, duck, view):
    got = q.listings(spark, SF, view).collect()
    assert len(got) == duck.execute("select count(*) from customer").fetchone()[0]
    assert sorted(map(repr, map(tuple, got))) == sorted(map(repr, duck.execute(__spark_entry__.oracle_sql()[f"{view}_listings"]).fetchall()))
    assert q.WHOLE[view.removesuffix("_all")] == view


def test_method_takes_similar_names(spark, monkeypatch):
    rows = [(1, "evergreen hardware", "5"), (2, "evergreen hardwares", "5"), (3, "evergreen hardware", "6")]
    df = spark.createDataFrame([(*r, None, None, "XX", "c", 1) for r in rows], "rid long, name string, phone string, url string, url2 string, state string, category string, gold long")
    monkeypatch.setattr(q, "listings", lambda *_: df)
    assert {r.rid: r.group_id for r in q.QUERIES["core_only"](spark, SF).collect()} == {1: 1, 2: 1, 3: 3}
    assert {r.group_id for r in q.QUERIES["same_name_95"](spark, SF).collect()} == {1}


def test_plan_has_no_cartesian_product(spark):
    plan = G.v_cliques(G.value_rows(q.listings(spark, SF)))._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan


def test_pairwise_measure(spark):
    pred = spark.createDataFrame([(1, 1), (2, 1), (3, 1), (4, 4)], "rid long, group_id long")
    gold = spark.createDataFrame([(1, 1), (2, 1), (3, 2), (4, 2)], "rid long, gold long")
    r = B.pairwise_prf(pred, gold).first()
    assert (r.tp, r.fp, r.fn, r.precision, r.recall, r.f) == (1, 2, 1, 0.333333, 0.5, 0.4)


def test_two_stage_is_first(spark):
    """On the random chains the method is before all baselines, in F and in recall before the one-stage methods."""
    got = {r.variant: r for r in q.QUERIES["overall_p1"](spark, SF).collect()}
    best = got.pop("two_stage")
    assert set(got) >= {"same_name", "connected_graph", "edge_partition", "edge_center", "edge_merge", "tfidf_two_stage"}
    assert all(best.f > r.f for r in got.values())
    assert all(best.recall > got[n].recall for n in q.ONE_STAGE)


def test_entry(spark):
    assert __spark_entry__.entry(spark).count() > 0


def test_shared_folder_must_be_named_on_a_cluster():
    from types import SimpleNamespace

    from chaincores.session import shared_dir

    def session(master, named=None):
        return SimpleNamespace(conf=SimpleNamespace(get=lambda *_: named), sparkContext=SimpleNamespace(master=master, getConf=lambda: SimpleNamespace(get=lambda *_: None)))

    assert shared_dir(session("local[8]")) and shared_dir(session("yarn", "hdfs://x/y/")) == "hdfs://x/y"
    for master in ("yarn", "local-cluster[3,2,3000]", "spark://h:7077"):
        with pytest.raises(RuntimeError):
            shared_dir(session(master))


def test_many_partitions_make_few_files(spark):
    from chaincores.session import FILES, materialise, release

    most = FILES * spark.sparkContext.defaultParallelism
    out = materialise(spark.range(5000).repartition(5 * most), "many")
    assert len(out.inputFiles()) <= most and sorted(r.id for r in out.collect()) == list(range(5000))
    release(out)


def test_entry_without_text_operators():
    import subprocess
    import sys

    code = "import sys; import importlib.abc\nclass No(importlib.abc.MetaPathFinder):\n    def find_spec(self, name, *_):\n        if name in ('chaincores.llm', 'corpus_pipeline'): raise ModuleNotFoundError(name=name)\nsys.meta_path.insert(0, No())\nimport __spark_entry__ as e; print(len(e.queries()), any(n.startswith('op') for n in e.queries()))"
    out = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, cwd=os.path.dirname(__spark_entry__.__file__))
    assert out.returncode == 0 and out.stdout.split()[1] == "False", out.stderr


def test_guard():
    assert os.path.exists("/root/testdata")
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


def test_many_users_are_counted_exactly(spark, tmp_path):
    spark.range(50_000).selectExpr("id % 20011 as user_id").unionByName(spark.sql("select cast(null as bigint) as user_id")).write.parquet(f"{tmp_path}/events.parquet")
    want = duckdb.sql(__spark_entry__.oracle_sql()["approximate_top_k"].replace("events", f"'{tmp_path}/events.parquet/*.parquet'")).fetchall()
    assert [tuple(r) for r in __spark_entry__.queries()["approximate_top_k"](spark, str(tmp_path)).collect()] == want == [(20012,)]


@pytest.mark.parametrize("threshold", [0.65, 0.8, 0.9, 0.95])
def test_similar_pairs_of_many_blocks_against_all_pairs(spark, monkeypatch, threshold):
    from chaincores.functions.text import jaro_winkler

    monkeypatch.setattr(G, "BLOCK", 40)
    rng = random.Random(8)
    names = {"".join(rng.choice(a) for _ in range(rng.randrange(lo, hi))) for a, lo, hi in (("0123456789abcdef", 10, 11), ("ab", 0, 7), ("abcdefghijklmnopqrstuvwxyzäé€ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789", 5, 60)) for _ in range(60)}
    names |= {n[:6] + "q" + n[6:] for n in list(names)[:40]} | {"😀 shop", "😀 shops", ""}
    want = sorted((a, b) for a in names for b in names if a < b and jaro_winkler(a, b) > threshold)
    got = G.similar_pairs(spark.createDataFrame([(n,) for n in [*names, None, "", *list(names)[:9]]], "name string"), threshold).collect()
    assert sorted((r.a, r.b) for r in got) == want and all(r.sim == jaro_winkler(r.a, r.b) for r in got)
    assert G.similar_pairs(spark.createDataFrame([], "name string"), threshold).count() == 0


def test_element_similarity_joins_no_groups_by_state_alone(spark):
    from chaincores import workloads

    # 20,000 groups of one state: all with all would be 400 million rows
    r = spark.range(20_000).selectExpr("id as rid", "concat('n', id) as name", "concat('p', id) as phone", "cast(null as string) as url", "cast(null as string) as url2", "'XX' as state", "'c' as category")
    e = workloads.element_similarities(r, r.selectExpr("rid", "rid as group_id")).collect()
    assert len(e) == 20_000 and all(x.rid == x.group_id for x in e) and len({round(x.sim, 9) for x in e}) == 1


def test_tfidf_lists_no_pairs_by_state_alone(spark, monkeypatch):
    """Satellites of one state are not joined with each core of it; the cores found are those of all pairs."""
    rng = random.Random(3)
    rows = [(i, f"n{i % 60 if i < 180 else rng.randrange(90)}", None, None, None, f"s{rng.randrange(2)}", f"c{rng.randrange(2)}") for i in range(600)]
    r = spark.createDataFrame(rows, "rid long, name string, phone string, url string, url2 string, state string, category string")
    cores = spark.createDataFrame([(i, i % 60) for i in range(180)], "rid long, core long")
    tables = {}
    monkeypatch.setattr(B, "materialise", lambda df, name, f=B.materialise: tables.setdefault(name, f(df, name)))
    got = {x.rid: x.group_id for x in B.tfidf_assign(r, cores).collect()}
    f = {}
    for rid, name, _, _, _, state, category in rows:
        f[rid] = {f"name={name}", f"state={state}", f"category={category}"}
    count = {x: sum(x in y for y in f.values()) for y in f.values() for x in y}
    idf = {x: math.log(600 / n) for x, n in count.items()}
    members = {c: [i for i in range(180) if i % 60 == c] for c in range(60)}
    for rid in range(180, 600):
        score = {c: round(sum(sum(x in f[i] for i in m) / len(m) * idf[x] ** 2 for x in f[rid]), 9) for c, m in members.items()}
        assert got[rid] == min(score, key=lambda c: (-score[c], c))
    assert all(got[i] == i % 60 for i in range(180))
    assert tables["near"].count() < 1000  # 420 satellites and 60 cores of two states and categories


def test_listings_and_names_are_found_once(spark, monkeypatch):
    """A query of the method writes its listings once, and presets of weights share one first stage."""
    calls = []
    for where, name in ((q, "listings"), (L, "close_names")):
        monkeypatch.setattr(where, name, lambda *a, f=getattr(where, name), name=name, **k: (calls.append(name), f(*a, **k))[1])
    q.QUERIES["initialise_exhaustive"](spark, SF)
    assert sorted(calls) == ["close_names", "listings"]
    calls.clear()
    want = q.compare(spark, [("fixed", L.two_stage(r := q.listings(spark, SF)), r)]).collect()
    calls.clear()
    got = q.QUERIES["ablation_presets"](spark, SF).collect()
    assert sorted(calls) == ["close_names", "listings"]
    assert [x for x in got if x.variant == "fixed"] == want and len(got) == 4


def test_ladder_has_the_cores_of_each_share(spark, monkeypatch):
    """One pass over all shares finds what a pass for each finds, also where a name's components are found beforehand."""
    from chaincores import workloads as w

    r = q.listings(spark, SF, "n2").withColumn("fifth", F.pmod(F.xxhash64("rid"), F.lit(5)))
    want = {}
    for n in (1, 5):
        comps = G.record_components(G.graph(r.where(F.col("fifth") < n)))
        want[20 * n] = (comps.select("comp").distinct().count(), comps.count())
    passes = []
    monkeypatch.setattr(G, "graph", lambda *a, f=G.graph: (passes.append(1), f(*a))[1])
    rows = w.QUERIES["ladder_times"](spark, SF).collect()
    assert {x.percent: (x.solved, x.nodes) for x in rows if x.strategy == "full" and x.percent in want} == want and not passes
    monkeypatch.setattr(C, "LOCAL_LIMIT", 0)
    plainly = lambda found: sorted((x.strategy, x.percent, x.solved, x.nodes, x.same) for x in found)
    assert plainly(w.QUERIES["ladder_times"](spark, SF).collect()) == plainly(rows)


def test_equal_records_make_no_pairs(spark):
    """3,000 records of one value would be 4.5 million pairs; their class has none but with the others."""
    rows = [(i, "n", "p" if i % 3 else None, "u", None, "x", "s" if i else "t", 0) for i in range(3000)]
    rows += [(3000, "n", "own", "u", None, None, "s", 0), (3001, "n", "p", "u", None, None, "s", 0), (3002, "m", "p", "u", None, "x", "s", 0)]
    r = spark.createDataFrame(rows, "rid long, name string, phone string, url string, url2 string, state string, category string, gold long")
    edges = B.alike(r)
    assert edges.classes.count() == 5 and edges.pairs.count() == 10 and edges.members.where("rid = 3002").isEmpty()
    for found in (B.edge_partition(r, edges=edges), B.edge_star(r, merge=True, edges=edges)):
        assert {x.rid: x.group_id for x in found.collect()} == {i: 3002 if i == 3002 else 0 for i in range(3003)}
    cores = {x.rid: x.core for x in B.agglomerative_cores(r, edges=edges).collect()}
    assert {cores[i] for i in range(1, 3000)} == {cores[1]} and 3002 not in cores


def test_other_cores_share_the_names(spark, monkeypatch):
    calls = []
    monkeypatch.setattr(L, "close_names", lambda *a, f=L.close_names: (calls.append(1), f(*a))[1])
    rows = {x.variant: x for x in q.QUERIES["ablation_edge_rule"](spark, SF).collect()}
    assert len(calls) == 1 and set(rows) == {"one_dominant", "two_dominant", "similarity"}
    r = q.listings(spark, SF)
    groups = L.cluster_elements(r, q._similar_edges(r), Settings(weights=q.learned(spark, SF)))
    assert q.compare(spark, [("similarity", groups, r)]).collect() == [rows["similarity"]]


@pytest.mark.parametrize("local", [0, 1000])
def test_components_find_their_edges_once(spark, local):
    seen = spark.sparkContext.accumulator(0)

    def count(batches):
        for batch in batches:
            seen.add(batch.num_rows)
            yield batch

    rows = [(1, 2), (2, 3), (3, 3), (9, 9), (5, 4), (4, 5), (None, 6), (7, None), (8, 8), (8, 8)]
    e = spark.createDataFrame(rows, "a long, b long").mapInArrow(count, "a long, b long")
    got = {(r.node, r.comp) for r in components(e, local=local).collect()}
    assert got == {(1, 1), (2, 1), (3, 1), (4, 4), (5, 4), (8, 8), (9, 9)} and seen.value == len(rows)


def test_names_are_dealt_to_few_blocks():
    # streets of 900,000 attendees: each block is sent to and prepared for every other one
    assert G.block_count(454_070, 6) == 28 and G.block_count(0, 6) == 1
    assert G.block_count(40_000, 6) == 9 and G.block_count(3000, 6) == 3  # work for all cores, where it is worth it


def test_pairs_above_equal_one_by_one():
    from chaincores.functions.text import jaro_winkler, pairs_above

    rng = random.Random(4)
    for alphabet, longest in (("ab", 5), ("abcdef 0123456789", 18), ("abcdefghijklmnopqrstuvwxyzäé€ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789", 48), ("abc", 52)):
        names = list({"".join(rng.choice(alphabet) for _ in range(rng.randrange(longest + 1))) for _ in range(70)})
        names += sorted({n[:3] + "c" + n[4:] for n in names[:30]} - set(names))
        for x, y in ((names, None), (names[:30], names[30:])):
            for t in (0.0, 0.7, 0.8, 0.9):
                met = [(min(a, b), max(a, b)) for i, a in enumerate(x) for b in (x[i + 1 :] if y is None else y)]
                want = sorted((a, b, jaro_winkler(a, b)) for a, b in met if jaro_winkler(a, b) > t)
                assert sorted((a, b, float(s)) for p, q, w in pairs_above(x, y, t) for a, b, s in zip(p, q, w, strict=True)) == want


def test_ablation_of_stages_finds_close_names_once(spark, monkeypatch):
    calls, find = [], L.close_names
    monkeypatch.setattr(L, "close_names", lambda *a: calls.append(a) or find(*a))
    got = {r.variant for r in __spark_entry__.queries()["ablation_stages"](spark, "/root/testdata/sf0.001").collect()}
    assert got == {"both", "core_only", "cluster_only"} and len(calls) == 1
