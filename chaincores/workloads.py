"""Further experiment workloads: keys, sizes, accuracy of cores, times by stage, strategy and share of the data, similarity of elements."""

from __future__ import annotations

import time
from collections import Counter
from collections.abc import Iterator
from itertools import groupby

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import window as W

from .operators import baselines as B
from .operators import cores as C
from .operators import graph as G
from .operators import keys as K
from .operators import linkage as L
from .plans import robust
from .plans.cluster import Settings, Weights
from .queries import BASE, COMP, CONNECTED, PRF, _natural, _SIG, _similar, clique_ctes, compare, ctes, gold, learned, method, method_cores, table
from .session import dealt, materialise
from .sources.planted import WHOLE, listings, listings_sql

QUERIES: dict = {}
ORACLES: dict = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


# --- keys ----------------------------------------------------------------------------------------------------------

#: How the attendees' values agree: area of the phone, server of the mail address, close street addresses.
RULES, CLOSE = {"phone": K.prefix(3), "url": K.email_server}, {"url2": 0.9}


def attendees(spark: SparkSession, sf: str) -> DataFrame:
    return K.dominant_keys(listings(spark, sf, "p5_raw"), RULES, CLOSE)


@query("dominant_keys", f"""WITH RECURSIVE r AS ({listings_sql('p5_raw')}), d AS (SELECT DISTINCT url2 AS a FROM r WHERE url2 IS NOT NULL), e AS (SELECT x.a AS x, y.a AS y FROM d x JOIN d y ON x.a = y.a OR jaro_winkler_similarity(x.a, y.a) > 0.9),
reach(x, y) AS (SELECT x, y FROM e UNION SELECT reach.x, e.y FROM reach JOIN e ON reach.y = e.x), k AS (SELECT x AS url2, min(y) AS street FROM reach GROUP BY x)
SELECT rid, substr(phone, 1, 3) AS phone, CASE WHEN url LIKE '%@%' THEN lower(regexp_extract(url, '@([^@\\s]+)$', 1)) END AS url, street FROM r LEFT JOIN k USING (url2)""")
def dominant_keys(spark, sf):
    return attendees(spark, sf).select("rid", "phone", "url", F.col("url2").alias("street"))


@query("organisation_linkage")
def organisation_linkage(spark, sf):
    """The attendees' raw values against canonical ones: without keys hardly anything is shared."""
    raw, r = materialise(listings(spark, sf, "p5_raw"), "listings"), materialise(attendees(spark, sf), "listings")
    s = Settings(weights=L.weights_of(L.learn_weights(r, gold(r), 300)))
    runs = [("raw", L.two_stage(raw, settings=s), raw), ("canonical", L.two_stage(r, settings=s), r), ("canonical_connected", B.connected_graph(r), r), ("same_affiliation", B.same_name(r, L.NAME), r)]
    return compare(spark, runs)


@query("v_cliques_two_common", f"WITH {ctes()}, {clique_ctes("SELECT DISTINCT v.rid, concat_ws('|', v.name || '/' || state, attr, value) AS clique FROM v JOIN r USING (rid) WHERE state IS NOT NULL")} SELECT rid, clique FROM c")
def v_cliques_two_common(spark, sf):
    """Cliques of records that agree in name and state, and share a dominant value."""
    return G.v_cliques(G.value_rows(K.common_key(listings(spark, sf), ["name", "state"])))


@query("graph_in_parts", f"{BASE} SELECT rid, clique FROM i")
def graph_in_parts(spark, sf):
    """The graph built by parts of the values equals the one built at once."""
    return K.graph_in_parts(G.value_rows(listings(spark, sf)), 3)


@query("url_domains", r"SELECT page_id, nullif(lower(regexp_extract(url, '^(?:[A-Za-z][A-Za-z0-9+.-]*://)?(?:www\.)?([^/?#:\s]+)', 1)), '') AS domain FROM pages")
def url_domains(spark, sf):
    return table(spark, sf, "pages").select("page_id", K.url_domain(F.col("url")).alias("domain"))


# --- sizes -----------------------------------------------------------------------------------------------------------

_EXACT = """ed AS (SELECT DISTINCT a.rid AS x, b.rid AS y FROM i a JOIN i b ON a.clique = b.clique AND a.rid < b.rid), m AS (SELECT cliques, m AS n, CASE WHEN m = 1 THEN min(rid) OVER (PARTITION BY cliques, m = 1) ELSE rid END AS node FROM ix), sn AS (SELECT node, min(cliques) AS cliques, min(n) AS n FROM m GROUP BY node)
SELECT (SELECT count(*) FROM ed) AS edges, count(*) AS index_entries, sum(m)::BIGINT AS index_rows, sum(length(cliques))::BIGINT AS index_chars, (SELECT count(*) FROM sn) AS simplified_entries, (SELECT sum(n)::BIGINT FROM sn) AS simplified_rows, (SELECT sum(length(cliques))::BIGINT FROM sn) AS simplified_chars,
round(1 - (SELECT count(*) FROM sn) / count(*)::DOUBLE, 6) AS smaller_by FROM ix"""
_LINES = "SELECT DISTINCT doc_id AS rid, concat_ws('|', lang, 'line', x) AS clique FROM (SELECT doc_id, lang, unnest(string_split(text, chr(10))) AS x FROM documents) WHERE length(x) >= 20 AND lang IS NOT NULL"


@query("graph_stats_exact", f"{BASE}, {_EXACT}")
def graph_stats_exact(spark, sf):
    return G.exact_stats(G.graph(listings(spark, sf)))


@query("graph_stats_documents", f"WITH {clique_ctes(_LINES)}, {_EXACT}")
def graph_stats_documents(spark, sf):
    """Sizes of the graph of documents of one language that share a line."""
    from .queries import v_cliques_documents

    return G.exact_stats(materialise(v_cliques_documents(spark, sf), "incidence"))


@query("graph_stats_part", f"WITH {clique_ctes("SELECT DISTINCT p_partkey AS rid, concat_ws('|', p_name, attr, x) AS clique FROM (SELECT p_partkey, p_name, 'brand' AS attr, p_brand AS x FROM part UNION ALL SELECT p_partkey, p_name, 'price', (p_retailprice * 100)::BIGINT::VARCHAR FROM part)")}, {_EXACT}")
def graph_stats_part(spark, sf):
    from .queries import v_cliques_part

    return G.exact_stats(materialise(v_cliques_part(spark, sf), "incidence"))


for _v, _all in WHOLE.items():
    query(f"gold_stats_{_v}", f"WITH {ctes(_all)}, n AS (SELECT gold, count(*) AS n FROM r GROUP BY gold) SELECT sum(n)::BIGINT AS n_records, count(*) FILTER (n > 1) AS n_groups, count(*) FILTER (n = 1) AS n_single, min(n) FILTER (n > 1) AS smallest, max(n) FILTER (n > 1) AS largest FROM n")(lambda spark, sf, v=_all: B.gold_stats(listings(spark, sf, v)))

_STATS = "n AS (SELECT block, count(*) AS n FROM b GROUP BY block HAVING count(*) > 1) SELECT count(*) AS n_blocks, max(n) AS largest, round(avg(n), 6) AS mean_size, round(avg((n < 100)::INT), 6) AS below_100 FROM n"
query("block_stats_close", f"WITH RECURSIVE k AS ({_similar(0.8)}), {ctes()}, b AS (SELECT rid, class AS block FROM r JOIN k USING (name)), {_STATS}")(lambda spark, sf: B.block_stats(L.blocks(listings(spark, sf), 0.8)))
query("block_stats_n2", f"WITH b AS (SELECT rid, name AS block FROM ({listings_sql('n2')})), {_STATS}")(lambda spark, sf: B.block_stats(L.blocks(listings(spark, sf, "n2"), None)))
query("block_stats_documents", f"WITH b AS (SELECT lang AS block FROM documents WHERE lang IS NOT NULL), {_STATS}")(lambda spark, sf: B.block_stats(L.blocks(table(spark, sf, "documents").where("lang is not null").select(F.col("doc_id").alias("rid"), F.col("lang").alias("name")), None)))


@query("core_metrics_summary")
def core_metrics_summary(spark, sf):
    """Components, screening and splitting over the order-based listings: calls, largest and mean input, share of small ones."""
    m = materialise(C.find_cores(G.graph(listings(spark, sf, "n2")), L.ROBUST, metrics=True), "metrics")
    share = lambda c: F.round(F.avg((F.col(c) < 10).cast("int")), 6)
    return m.agg(F.count("*").alias("components"), F.max("nodes").alias("largest"), F.round(F.avg("nodes"), 6).alias("mean_nodes"), share("nodes").alias("below_10"), F.sum("screens").alias("screens"), F.max("largest_screen").alias("largest_screen"), F.sum("splits").alias("splits"), F.max("largest_split").alias("largest_split"), F.sum("cores").alias("cores"))


# --- accuracy of cores, times ------------------------------------------------------------------------------------------


def _cores_as_groups(r: DataFrame, cores: DataFrame) -> DataFrame:
    return L.elements(r, cores).select("rid", F.col("eid").alias("group_id"))


@query("prf_cores")
def prf_cores(spark, sf):
    """Pairs within cores against the known groups, by strategy and edge rule."""
    r = materialise(listings(spark, sf), "listings")
    i = G.graph(r, L.NAME)
    from .queries import _similar_edges, classed

    named = materialise(classed(r), "classed")
    found = {s: C.find_cores(i, L.ROBUST, s) for s in ("full", "screen_only")}
    found |= {"agglomerative": B.agglomerative_cores(r), "two_dominant": C.find_cores(G.two_dominant_cliques(G.value_rows(named)), L.ROBUST), "similarity": _similar_edges(r)}
    return compare(spark, [(name, _cores_as_groups(r, c), r) for name, c in found.items()])


@query("prf_cores_k0", f"{CONNECTED}, {PRF}")
def prf_cores_k0(spark, sf):
    r = listings(spark, sf)
    return B.pairwise_prf(_cores_as_groups(r, C.find_cores(G.graph(r), 0)), gold(r))


@query("stage_times")
def stage_times(spark, sf):
    """Seconds of each stage of the whole method on the random chains, every stage written out."""
    rows, last = [], time.time()

    def done(stage: str, df: DataFrame) -> DataFrame:
        nonlocal last
        out = materialise(df, stage)
        rows.append((stage, out.count(), round(time.time() - last, 3)))
        last = time.time()
        return out

    r = done("records", listings(spark, sf))
    pairs = done("names", L.close_names(r))
    graph = done("graph", G.graph(r, L.NAME, pairs))
    cores = done("cores", C.find_cores(graph, L.ROBUST))
    packed = L.pack(r, cores, L.CLOSE, pairs)
    done("blocking", packed.rows)
    weights = learned(spark, sf, records=r)
    last = time.time()
    done("clustering", L.assign(packed, Settings(weights=weights)))
    return spark.createDataFrame(rows, "stage string, n_rows long, seconds double")


#: Nodes of a component beyond which raw edges, and cliques without unions, are not tried: their time grows with the square of their pairs.
LADDER = {"naive": 12, "index": 150, "sindex": 150, "union": None, "full": None}


@query("ladder_times")
def ladder_times(spark, sf):
    """Seconds in tasks by strategy and share of the order-based listings, over the same components; ``solved`` counts those
    that the strategy was tried on, ``same`` those of them with the cores of ``full``."""
    v = materialise(G.value_rows(listings(spark, sf, "n2")), "values")
    # a clique begins with its name's hash, and names share no clique: what is in one key is whole components
    named = v.withColumn("name", F.concat_ws("|", F.xxhash64("name").cast("string"), "name"))
    whole = materialise(G.v_cliques(named), "cliques")
    # cliques of a share are among those of all: a record is in its own fifth's share and the larger ones, under other ids
    n = F.explode(F.sequence(F.pmod(F.xxhash64("rid"), F.lit(5)) + 1, F.lit(5).cast("long"))).alias("n")
    each = whole.select("rid", "clique", n).select((F.col("rid") * 5 + F.col("n") - 1).alias("rid"), F.concat_ws("|", F.col("n").cast("string"), "clique").alias("clique"))
    every = materialise(G.prune_subcliques(materialise(each.join(each.groupBy("clique").count().where("count > 1").select("clique"), "clique"), "shares")), "incidence")
    every = every.withColumn("key", F.substring_index("clique", "|", 2))
    large = materialise(every.groupBy("key").count().where(F.col("count") > C.LOCAL_LIMIT).select("key"), "large")
    if not large.isEmpty():
        of_large = materialise(every.join(large, "key"), "of_large")
        parted = of_large.join(G.record_components(of_large.select("rid", "clique")), "rid").select("rid", "clique", F.concat_ws("|", F.substring_index("key", "|", 1), F.col("comp").cast("string")).alias("key"))
        every = every.join(large, "key", "left_anti").select("rid", "clique", "key").unionByName(parted)

    def climb(percent: int, cliques: list[frozenset], nodes: list, found: dict) -> None:
        where: dict = {}
        for j, c in enumerate(cliques):
            for x in c:
                where.setdefault(x, []).append(j)
        # one record stands for all that lie in the same single clique
        low = [min((y for y in c if len(where[y]) == 1), default=None) for c in cliques]
        stands = {x: low[where[x][0]] if len(where[x]) == 1 else x for x in nodes}
        weight = Counter(stands.values())
        small = [frozenset(stands[x] for x in c) for c in cliques]
        want = None
        for strategy in reversed(LADDER):
            if LADDER[strategy] is not None and len(nodes) > LADDER[strategy]:
                continue
            simple = robust.STRATEGIES[strategy][0]
            begun = time.perf_counter()
            got = robust.solve(small if simple else cliques, weight if simple else dict.fromkeys(nodes, 1), L.ROBUST, strategy)
            took = time.perf_counter() - begun
            if simple:
                back: dict = {}
                for x in nodes:
                    back.setdefault(stands[x], set()).add(x)
                got = sorted((set().union(*(back[x] for x in c)) for c in got), key=min)
            want = got if want is None else want
            for k, x in enumerate((1, len(nodes), took, got == want)):
                found.setdefault((strategy, percent), [0, 0, 0.0, 0])[k] += x

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: dict = {}
        rows = ((k, c, x) for batch in batches for k, c, x in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True))
        for key, group in groupby(rows, lambda x: x[0]):
            members: dict = {}
            for _, c, x in group:
                members.setdefault(c, []).append(x)
            cliques = [frozenset(members[c]) for c in sorted(members)]
            every_node = set().union(*cliques)
            parts = robust.pieces(every_node, cliques)
            at = {x: j for j, part in enumerate(parts) for x in part}
            own: list = [[] for _ in parts]
            for c in cliques:
                own[at[next(iter(c))]].append(c)
            for part, c in zip(parts, own, strict=True):
                climb(20 * int(key.partition("|")[0]), c, sorted(part), found)
        if found:
            columns = [pa.array([s for s, _ in found]), pa.array([p for _, p in found], pa.int32()), *(pa.array([f[k] for f in found.values()], t) for k, t in enumerate((pa.int64(), pa.int64(), pa.float64(), pa.int64())))]
            yield pa.record_batch(columns, names=["strategy", "percent", "solved", "nodes", "seconds", "same"])

    got = dealt(every.select("key", "clique", "rid"), "key").sortWithinPartitions("key").mapInArrow(run, "strategy string, percent int, solved long, nodes long, seconds double, same long")
    return got.groupBy("strategy", "percent").agg(F.sum("solved").alias("solved"), F.sum("nodes").alias("nodes"), F.round(F.sum("seconds"), 6).alias("seconds"), F.sum("same").alias("same"))


def with_delta(df: DataFrame, first: str) -> DataFrame:
    """``df`` of variants with the change of F against the first one."""
    base = df.where(F.col("variant") == first).select(F.col("f").alias("f0"))  # one row
    return df.crossJoin(base).withColumn("delta_f", F.round(F.col("f") - F.col("f0"), 6)).drop("f0")


for _s, _first in (("sweep_k", "k2"), ("sweep_p", "p0.8"), ("sweep_theta", "theta0.6"), ("sweep_name", "name0.95")):

    def _delta(spark, sf, s=_s, first=_first):
        from .queries import QUERIES as runs

        return with_delta(materialise(runs[s](spark, sf), "sweep"), first)

    query(f"{_s}_delta")(_delta)


# --- similarity of elements --------------------------------------------------------------------------------------------

_W = Weights((0.5, 0.5), (0.9, 0.5), mode="single")
_PARTS = f"""{_SIG}, dm AS (SELECT v.rid, group_id, 1 - product(1 - 0.8::DOUBLE * w) AS dom FROM v JOIN sg USING (attr, value) GROUP BY ALL),
nm AS (SELECT group_id, name, count(*) / max(size)::DOUBLE AS w FROM r JOIN g USING (rid) JOIN z USING (group_id) GROUP BY ALL), nq AS (SELECT group_id, sqrt(sum(w * w)) AS q FROM nm GROUP BY group_id), cm AS (SELECT rid, group_id, w / q AS com FROM r JOIN nm USING (name) JOIN nq USING (group_id)),
mu AS (SELECT group_id, attr, value, count(*) / max(size)::DOUBLE AS w FROM (SELECT rid, 'state' AS attr, state AS value FROM r UNION ALL SELECT rid, 'category', category FROM r) JOIN g USING (rid) JOIN z USING (group_id) WHERE value IS NOT NULL GROUP BY ALL),
el AS (SELECT rid, group_id, coalesce(com, 0.0::DOUBLE) AS com, coalesce(dom, 0.0::DOUBLE) AS dom FROM cm FULL JOIN dm USING (rid, group_id)),
st AS (SELECT *, (0.5::DOUBLE * com + (0.9::DOUBLE * dom + 0.5::DOUBLE * (1 - dom)) * dom) / (0.5::DOUBLE + 0.9::DOUBLE * dom + 0.5::DOUBLE * (1 - dom)) AS strong FROM el),
es AS (SELECT st.rid, st.group_id, com, dom, least(1.0::DOUBLE, strong + CASE WHEN strong >= 0.6 - 1e-9 THEN 0.1::DOUBLE * (coalesce(ms.w, 0.0::DOUBLE) + coalesce(mc.w, 0.0::DOUBLE)) ELSE 0.0::DOUBLE END) AS sim
  FROM st JOIN r USING (rid) LEFT JOIN mu ms ON ms.group_id = st.group_id AND ms.attr = 'state' AND ms.value = r.state LEFT JOIN mu mc ON mc.group_id = st.group_id AND mc.attr = 'category' AND mc.value = r.category)"""


def element_similarities(r: DataFrame, groups: DataFrame, s: Settings = Settings(weights=_W)) -> DataFrame:
    """rid, group_id, com, dom, sim: similarity of single records to the groups that share their name or a dominant value."""
    w, owner = s.weights, groups.select(F.col("group_id").alias("owner"), "rid")
    v = G.value_rows(r)
    sig = L.signatures(owner, v)
    dom = v.join(sig, ["attr", "value"]).groupBy("rid", F.col("owner").alias("group_id")).agg((1 - F.exp(F.sum(F.log1p(-s.p * F.col("weight"))))).alias("dom"))
    names = L.signatures(owner, r.where("name is not null").select("rid", F.lit("name").alias("attr"), F.col("name").alias("value")))
    norm = names.groupBy("owner").agg(F.sqrt(F.sum(F.col("weight") * F.col("weight"))).alias("q"))
    com = r.select("rid", F.col("name").alias("value")).join(names, "value").join(norm, "owner").select("rid", F.col("owner").alias("group_id"), (F.col("weight") / F.col("q")).alias("com"))
    both = com.join(dom, ["rid", "group_id"], "full").select("rid", "group_id", F.coalesce("com", F.lit(0.0)).alias("com"), F.coalesce("dom", F.lit(0.0)).alias("dom"))
    effective = lambda role, x: F.col(x) * getattr(w, role)[0] + (1 - F.col(x)) * getattr(w, role)[1]
    wc, wd = effective("com", "com"), effective("dom", "dom")
    both = both.withColumn("strong", (wc * F.col("com") + wd * F.col("dom")) / (wc + wd))
    multi = r.select("rid", F.explode(F.array(*[F.struct(F.lit(a).alias("attr"), F.col(a).alias("value")) for a in ("state", "category")])).alias("m")).select("rid", "m.*").where("value is not null")
    # only pairs that share a name or a dominant value count, and states or categories alone would join all with all
    held = L.signatures(owner, multi).withColumnRenamed("owner", "group_id")
    shared = both.select("rid", "group_id").join(multi, "rid").join(held, ["group_id", "attr", "value"]).groupBy("rid", "group_id").agg(F.sum("weight").alias("multi"))
    both = both.join(shared, ["rid", "group_id"], "left")
    more = F.when(F.col("strong") >= s.theta - 1e-9, w.multi * F.coalesce("multi", F.lit(0.0))).otherwise(0.0)
    return both.select("rid", "group_id", "com", "dom", F.least(F.lit(1.0), F.col("strong") + more).alias("sim"))


@query("element_similarity", f"{_PARTS} SELECT rid, group_id, round(com, 6) AS com, round(dom, 6) AS dom, round(sim, 6) AS sim FROM es")
def element_similarity(spark, sf):
    r = listings(spark, sf)
    e = element_similarities(r, materialise(B.connected_graph(r), "groups"))
    return e.select("rid", "group_id", *[F.round(c, 6).alias(c) for c in ("com", "dom", "sim")])


_SCORE = f"""{_PARTS}, j AS (SELECT es.rid, es.group_id AS cluster, g.group_id AS own, round(sim, 9) AS sim FROM es JOIN g ON g.rid = es.rid),
oth AS (SELECT rid, cluster AS near, sim AS b FROM j WHERE cluster <> own QUALIFY row_number() OVER (PARTITION BY rid ORDER BY sim DESC, cluster) = 1),
sc AS (SELECT j.rid, own, near, sim AS a, coalesce(b, 0.0::DOUBLE) AS b, (sim - coalesce(b, 0.0::DOUBLE) + 0.01::DOUBLE) / (greatest(sim, coalesce(b, 0.0::DOUBLE)) + 0.02::DOUBLE) AS s FROM j LEFT JOIN oth USING (rid) WHERE cluster = own)"""


def scored(r: DataFrame, groups: DataFrame, s: Settings = Settings(weights=_W)) -> DataFrame:
    """rid, own, near, a, b, s: silhouette of each record in its group, and its nearest other group (the smaller of equals)."""
    sims = materialise(element_similarities(r, groups, s).withColumn("sim", F.round("sim", 9)).join(groups.withColumnRenamed("group_id", "own"), "rid"), "sims")
    first = W.Window.partitionBy("rid").orderBy(F.desc("sim"), "group_id")
    near = sims.where("group_id <> own").withColumn("at", F.row_number().over(first)).where("at = 1").select("rid", F.col("group_id").alias("near"), F.col("sim").alias("b"))
    both = sims.where("group_id = own").select("rid", "own", F.col("sim").alias("a")).join(near, "rid", "left").withColumn("b", F.coalesce("b", F.lit(0.0)))
    return both.withColumn("s", (F.col("a") - F.col("b") + s.alpha) / (F.greatest("a", "b") + s.beta))


@query("sv_index", f"{_SCORE} SELECT count(*) AS n, round(avg(s), 6) AS sv_index FROM sc")
def sv_index(spark, sf):
    r = listings(spark, sf)
    return scored(r, materialise(B.connected_graph(r), "groups")).agg(F.count("*").alias("n"), F.round(F.avg("s"), 6).alias("sv_index"))


@query("candidate_pairs", f"{_SCORE} SELECT least(own, near) AS c1, greatest(own, near) AS c2, count(*) AS n_border, round(sum(1 - s), 6) AS benefit FROM sc WHERE near IS NOT NULL AND s <= 0.3 GROUP BY ALL")
def candidate_pairs(spark, sf):
    """Pairs of groups that border records lie between, with the benefit of treating each."""
    r = listings(spark, sf)
    border = scored(r, materialise(B.connected_graph(r), "groups")).where(F.col("near").isNotNull() & (F.col("s") <= Settings().border))
    return border.groupBy(F.least("own", "near").alias("c1"), F.greatest("own", "near").alias("c2")).agg(F.count("*").alias("n_border"), F.round(F.sum(1 - F.col("s")), 6).alias("benefit"))


@query("weighted_edges", f"""WITH {ctes()}, pv AS (SELECT rid, 'phone' AS attr, phone AS value FROM r WHERE phone IS NOT NULL AND name IS NOT NULL UNION ALL SELECT rid, 'url', url FROM r WHERE url IS NOT NULL AND name IS NOT NULL),
pd AS (SELECT a.rid AS r1, b.rid AS r2, count(*) * 0.25::DOUBLE AS dom FROM pv a JOIN pv b ON a.attr = b.attr AND a.value = b.value AND a.rid < b.rid GROUP BY ALL),
ps AS (SELECT r1, r2, dom + 0.4::DOUBLE * jaro_winkler_similarity(x.name, y.name) + CASE WHEN x.category = y.category THEN 0.1::DOUBLE ELSE 0.0::DOUBLE END AS sim FROM pd JOIN r x ON x.rid = r1 JOIN r y ON y.rid = r2)
SELECT r1, r2, round(sim, 6) AS sim FROM ps WHERE sim > 0.8""")
def weighted_edges(spark, sf):
    """Edges of the rule that compares all attributes but the location."""
    return B.weighted_pairs(listings(spark, sf)).withColumn("sim", F.round("sim", 6))


@query("silhouette_method")
def silhouette_method(spark, sf):
    """Index of the whole method's groups, and of the one-stage groups, under the same similarity."""
    r = materialise(listings(spark, sf), "listings")
    out = None
    for name, g in (("two_stage", method(spark, sf)), ("connected_graph", B.connected_graph(r)), ("same_name", B.same_name(r, L.NAME))):
        row = scored(r, materialise(g.select("rid", "group_id"), "groups")).agg(F.round(F.avg("s"), 6).alias("sv_index")).withColumn("variant", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out
