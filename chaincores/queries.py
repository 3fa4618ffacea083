"""Queries of the linkage methods over planted and natural views, and the same rows in DuckDB SQL where SQL can say them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.text import jaro_winkler_udf
from .operators import baselines as B
from .operators import cores as C
from .operators import graph as G
from .operators import linkage as L
from .plans.cluster import PRESETS, Settings, Weights
from .session import materialise
from .sources.planted import VIEWS, WHOLE, listings, listings_sql

QUERIES: dict = {}
ORACLES: dict = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def gold(r: DataFrame) -> DataFrame:
    return r.select("rid", "gold")


def method_cores(r: DataFrame) -> DataFrame:
    """Cores as the method defines them: similar names, and the standard robustness."""
    return materialise(C.find_cores(G.graph(r, L.NAME), L.ROBUST), "cores")


#: Labelled records that the weights are learned from: of the random chains for all listings, of the attendees for themselves.
SAMPLE, ATTENDEES = 1000, 300


def learned(spark, sf, view: str = "p1", mode: str = "double", records: DataFrame | None = None) -> Weights:
    """The weights that the method runs with on a view; ``records`` are the view's, if they are written out."""
    own = view.startswith("p5")
    of = WHOLE["p5"] if own else "p1"
    r = records if records is not None and view == of else materialise(listings(spark, sf, of), "labelled")
    return L.weights_of(L.learn_weights(r, gold(r), ATTENDEES if own else SAMPLE), mode)


def method(spark, sf, view: str = "p1", **how) -> DataFrame:
    """The whole method with learned weights; ``how`` are options of ``two_stage``."""
    settings = how.pop("settings", Settings())
    r = materialise(listings(spark, sf, view), "listings")
    return L.two_stage(r, settings=settings.but(weights=learned(spark, sf, view, records=r)), **how)


def classed(r: DataFrame) -> DataFrame:
    """Records under the name of their class, for edge rules that compare names by equality."""
    return r.join(G.name_classes(r, L.NAME), "name").withColumn("name", F.col("class")).drop("class")


# --- SQL building blocks -----------------------------------------------------------------------------------------


def ctes(view: str = "p1") -> str:
    return f"""r AS ({listings_sql(view)}),
v AS (SELECT DISTINCT rid, name, attr, value FROM (SELECT rid, name, 'phone' AS attr, phone AS value FROM r UNION ALL SELECT rid, name, 'url', url FROM r UNION ALL SELECT rid, name, 'url', url2 FROM r)
  WHERE value IS NOT NULL AND trim(value) <> '' AND rid IS NOT NULL AND name IS NOT NULL)"""


def clique_ctes(keyed: str = "SELECT DISTINCT rid, concat_ws('|', name, attr, value) AS clique FROM v") -> str:
    return f"""c AS (SELECT rid, clique FROM (SELECT *, count(*) OVER (PARTITION BY clique) AS n FROM ({keyed})) WHERE n > 1),
o AS (SELECT a.clique AS c1, b.clique AS c2, count(*) AS n FROM c a JOIN c b ON a.rid = b.rid AND a.clique < b.clique GROUP BY ALL),
s AS (SELECT clique, count(*) AS size FROM c GROUP BY clique),
gone AS (SELECT c1 AS clique FROM o JOIN s x ON x.clique = c1 JOIN s y ON y.clique = c2 WHERE n = x.size AND x.size < y.size
  UNION SELECT c2 FROM o JOIN s x ON x.clique = c1 JOIN s y ON y.clique = c2 WHERE n = y.size AND y.size <= x.size),
i AS (SELECT rid, clique FROM c WHERE clique NOT IN (SELECT clique FROM gone)),
ix AS (SELECT rid, string_agg(clique, ';' ORDER BY clique) AS cliques, count(*) AS m FROM i GROUP BY rid)"""


COMP = """e AS (SELECT DISTINCT a.rid AS x, b.rid AS y FROM i a JOIN i b ON a.clique = b.clique),
reach(x, y) AS (SELECT x, y FROM e UNION SELECT reach.x, e.y FROM reach JOIN e ON reach.y = e.x),
comp AS (SELECT x AS rid, min(y) AS comp FROM reach GROUP BY x)"""
BASE = f"WITH RECURSIVE {ctes()}, {clique_ctes()}"
CONNECTED = f"{BASE}, {COMP}, g AS (SELECT r.rid, coalesce(comp, r.rid) AS group_id FROM r LEFT JOIN comp USING (rid))"
PRF = """cell AS (SELECT group_id, gold, count(*) AS n FROM r JOIN g USING (rid) GROUP BY ALL),
t AS (SELECT coalesce(sum(n * (n - 1) // 2), 0)::BIGINT AS tp FROM cell), p AS (SELECT coalesce(sum(n * (n - 1) // 2), 0)::BIGINT AS p FROM (SELECT sum(n)::BIGINT AS n FROM cell GROUP BY group_id)),
q AS (SELECT coalesce(sum(n * (n - 1) // 2), 0)::BIGINT AS q FROM (SELECT count(*) AS n FROM r GROUP BY gold))
SELECT tp, p - tp AS fp, q - tp AS fn, round(CASE WHEN p > 0 THEN tp / p::DOUBLE END, 6) AS precision, round(CASE WHEN q > 0 THEN tp / q::DOUBLE END, 6) AS recall,
round(CASE WHEN p + q > 0 THEN 2 * tp / (p + q)::DOUBLE END, 6) AS f FROM t, p, q"""
SAME = "g AS (SELECT rid, coalesce(min(rid) OVER (PARTITION BY name), rid) AS group_id FROM r)"
FEATURES = """f AS (SELECT DISTINCT rid, concat_ws('=', a, x) AS feature FROM (SELECT rid, 'name' AS a, name AS x FROM r UNION ALL SELECT rid, 'phone', phone FROM r UNION ALL SELECT rid, 'url', url FROM r
  UNION ALL SELECT rid, 'url', url2 FROM r UNION ALL SELECT rid, 'state', state FROM r UNION ALL SELECT rid, 'category', category FROM r) WHERE x IS NOT NULL)"""
PAIRS = """pr AS (SELECT a.rid AS r1, b.rid AS r2, count(*) AS n FROM v a JOIN v b ON a.name = b.name AND a.attr = b.attr AND a.value = b.value AND a.rid < b.rid GROUP BY ALL),
ps AS (SELECT r1, r2, least(1.0::DOUBLE, 0.5::DOUBLE + 0.5::DOUBLE * (1 - (1 - 0.8::DOUBLE) ** n) * 0.8::DOUBLE + (CASE WHEN x.state = y.state THEN 0.1::DOUBLE ELSE 0.0::DOUBLE END + CASE WHEN x.category = y.category THEN 0.1::DOUBLE ELSE 0.0::DOUBLE END)) AS sim
  FROM pr JOIN r x ON x.rid = r1 JOIN r y ON y.rid = r2)"""

# --- planted data and graph ----------------------------------------------------------------------------------------

for _v in VIEWS:
    query(f"{_v}_listings", listings_sql(_v))(lambda spark, sf, v=_v: listings(spark, sf, v))


@query("gold_stats", f"WITH {ctes()}, n AS (SELECT gold, count(*) AS n FROM r GROUP BY gold) SELECT sum(n)::BIGINT AS n_records, count(*) FILTER (n > 1) AS n_groups, count(*) FILTER (n = 1) AS n_single, min(n) FILTER (n > 1) AS smallest, max(n) FILTER (n > 1) AS largest FROM n")
def gold_stats(spark, sf):
    return B.gold_stats(listings(spark, sf))


@query("value_rows", f"WITH {ctes()} SELECT * FROM v")
def value_rows(spark, sf):
    return G.value_rows(listings(spark, sf))


@query("name_classes_exact", f"WITH {ctes()} SELECT DISTINCT name, name AS class FROM r WHERE name IS NOT NULL")
def name_classes_exact(spark, sf):
    return G.name_classes(listings(spark, sf))


def _similar(t: float) -> str:
    return f"""WITH RECURSIVE {ctes()}, d AS (SELECT DISTINCT name FROM r WHERE name IS NOT NULL),
e AS (SELECT a.name AS x, b.name AS y FROM d a JOIN d b ON a.name = b.name OR jaro_winkler_similarity(a.name, b.name) > {t}),
reach(x, y) AS (SELECT x, y FROM e UNION SELECT reach.x, e.y FROM reach JOIN e ON reach.y = e.x) SELECT x AS name, min(y) AS class FROM reach GROUP BY x"""


query("name_classes_similar_80", _similar(0.8))(lambda spark, sf: G.name_classes(listings(spark, sf), 0.8))
query("name_classes_similar_95", _similar(0.95))(lambda spark, sf: G.name_classes(listings(spark, sf), 0.95))


@query("jaro_winkler_names", f"WITH {ctes()}, d AS (SELECT DISTINCT name FROM r WHERE name IS NOT NULL) SELECT a.name AS a, b.name AS b, round(jaro_winkler_similarity(a.name, b.name), 6) AS sim FROM d a JOIN d b ON a.name < b.name AND substr(a.name, 1, 3) = substr(b.name, 1, 3)")
def jaro_winkler_names(spark, sf):
    d = listings(spark, sf).select("name").distinct().where("name is not null").withColumn("k", F.substring("name", 1, 3))
    pairs = d.withColumnRenamed("name", "a").join(d.withColumnRenamed("name", "b"), "k").where("a < b")
    return pairs.select("a", "b", F.round(jaro_winkler_udf(F.col("a"), F.col("b")), 6).alias("sim"))


def _above(names: str, t: float) -> str:
    return f"SELECT a.name AS a, b.name AS b, round(jaro_winkler_similarity(a.name, b.name), 6) AS sim FROM {names} a JOIN {names} b ON a.name < b.name AND jaro_winkler_similarity(a.name, b.name) > {t}"


query("jaro_winkler_names_80", f"WITH {ctes()}, d AS (SELECT DISTINCT name FROM r WHERE name IS NOT NULL) {_above('d', 0.8)}")(lambda spark, sf: G.similar_pairs(listings(spark, sf), 0.8).withColumn("sim", F.round("sim", 6)))
query("jaro_winkler_parts_80", f"WITH d AS (SELECT DISTINCT p_name AS name FROM part WHERE p_name IS NOT NULL) {_above('d', 0.8)}")(lambda spark, sf: G.similar_pairs(table(spark, sf, "part").select(F.col("p_name").alias("name")), 0.8).withColumn("sim", F.round("sim", 6)))


@query("v_cliques_p1", f"{BASE} SELECT rid, clique FROM c")
def v_cliques_p1(spark, sf):
    return G.v_cliques(G.value_rows(listings(spark, sf)))


def _natural(sql: str) -> str:
    return f"WITH {clique_ctes(sql)} SELECT rid, clique FROM i"


@query("v_cliques_part", _natural("SELECT DISTINCT p_partkey AS rid, concat_ws('|', p_name, attr, x) AS clique FROM (SELECT p_partkey, p_name, 'brand' AS attr, p_brand AS x FROM part UNION ALL SELECT p_partkey, p_name, 'price', (p_retailprice * 100)::BIGINT::VARCHAR FROM part)"))
def v_cliques_part(spark, sf):
    p = table(spark, sf, "part").select(F.col("p_partkey").alias("rid"), F.col("p_name").alias("name"), F.col("p_brand").alias("brand"), F.round(F.col("p_retailprice") * 100).cast("long").cast("string").alias("price"))
    return G.prune_subcliques(G.v_cliques(G.value_rows(p, ("brand", "price"))))


@query("v_cliques_events", _natural("SELECT DISTINCT event_id AS rid, concat_ws('|', event_type, attr, x) AS clique FROM (SELECT event_id, event_type, 'user' AS attr, user_id::VARCHAR AS x FROM events UNION ALL SELECT event_id, event_type, 'k', json_extract_string(props, '$.k') FROM events) WHERE x IS NOT NULL"))
def v_cliques_events(spark, sf):
    e = table(spark, sf, "events").select(F.col("event_id").alias("rid"), F.col("event_type").alias("name"), F.col("user_id").cast("string").alias("user"), F.get_json_object("props", "$.k").alias("k"))
    return G.prune_subcliques(G.v_cliques(G.value_rows(e, ("user", "k"))))


@query("v_cliques_documents", _natural("SELECT DISTINCT doc_id AS rid, concat_ws('|', lang, 'line', x) AS clique FROM (SELECT doc_id, lang, unnest(string_split(text, chr(10))) AS x FROM documents) WHERE length(x) >= 20 AND lang IS NOT NULL"))
def v_cliques_documents(spark, sf):
    d = table(spark, sf, "documents").where("lang is not null").select(F.col("doc_id").alias("rid"), "lang", F.explode(F.split("text", "\n")).alias("value")).where("length(value) >= 20")
    return G.prune_subcliques(G.v_cliques(d.select("rid", F.col("lang").alias("name"), F.lit("line").alias("attr"), "value").distinct()))


@query("prune_subcliques", f"{BASE} SELECT rid, clique FROM i")
def prune(spark, sf):
    return G.graph(listings(spark, sf))


@query("clique_overlaps", f"{BASE} SELECT c1, c2, n FROM o")
def clique_overlaps(spark, sf):
    return G.overlaps(G.v_cliques(G.value_rows(listings(spark, sf))))


@query("inverted_index", f"{BASE} SELECT rid, cliques FROM ix")
def inverted_index(spark, sf):
    return G.inverted_index(G.graph(listings(spark, sf))).select("rid", F.concat_ws(";", "cliques").alias("cliques"))


@query("simplified_index", f"{BASE}, m AS (SELECT rid, CASE WHEN m = 1 THEN min(rid) OVER (PARTITION BY cliques, m = 1) ELSE rid END AS node, cliques FROM ix) SELECT node, count(*) AS weight, min(cliques) AS cliques FROM m GROUP BY node")
def simplified_index(spark, sf):
    return G.simplify(G.graph(listings(spark, sf)))[0].select("node", "weight", F.concat_ws(";", "cliques").alias("cliques"))


@query("two_dominant_cliques", f"WITH {ctes()}, k AS (SELECT rid, name, attr || '|' || value AS x FROM v), {clique_ctes("SELECT DISTINCT a.rid, concat_ws('|', a.name, a.x, b.x) AS clique FROM k a JOIN k b ON a.rid = b.rid AND a.x < b.x")} SELECT rid, clique FROM c")
def two_dominant(spark, sf):
    return G.two_dominant_cliques(G.value_rows(listings(spark, sf)))


@query("similarity_edges", f"WITH {ctes()}, {PAIRS} SELECT r1, r2, round(sim, 6) AS sim FROM ps WHERE sim > 0.8")
def similarity_edges(spark, sf):
    return B.record_pairs(listings(spark, sf)).where("sim > 0.8").withColumn("sim", F.round("sim", 6))


@query("graph_stats", f"""{BASE}, z AS (SELECT clique, count(*) AS s FROM i GROUP BY clique), m AS (SELECT CASE WHEN m = 1 THEN min(rid) OVER (PARTITION BY cliques, m = 1) ELSE rid END AS node FROM ix), n AS (SELECT node, count(*) AS w FROM m GROUP BY node)
SELECT (SELECT count(*) FROM z) AS cliques, (SELECT sum(s)::BIGINT FROM z) AS incidences, (SELECT sum(s * (s - 1) // 2)::BIGINT FROM z) AS edge_bound, (SELECT max(s) FROM z) AS largest_clique, (SELECT count(*) FROM ix) AS records, (SELECT max(m) FROM ix) AS most_cliques, (SELECT count(*) FROM n) AS nodes, (SELECT max(w) FROM n) AS largest_node""")
def graph_stats(spark, sf):
    return G.graph_stats(G.graph(listings(spark, sf)))


@query("components_p1", f"{BASE}, {COMP} SELECT rid, comp FROM comp")
def components_p1(spark, sf):
    return G.record_components(G.graph(listings(spark, sf)))


@query("components_part", f"WITH RECURSIVE {clique_ctes("SELECT DISTINCT p_partkey AS rid, concat_ws('|', p_name, 'brand', p_brand) AS clique FROM part")}, {COMP} SELECT rid, comp FROM comp")
def components_part(spark, sf):
    p = table(spark, sf, "part").select(F.col("p_partkey").alias("rid"), F.col("p_name").alias("name"), F.col("p_brand").alias("brand"))
    return G.record_components(G.prune_subcliques(G.v_cliques(G.value_rows(p, ("brand",)))))


# --- cores ---------------------------------------------------------------------------------------------------------

UNIONS = """ov AS (SELECT a.clique AS x, b.clique AS y, count(*) AS n FROM i a JOIN i b ON a.rid = b.rid AND a.clique <> b.clique GROUP BY ALL HAVING count(*) > {k}),
ur(x, y) AS (SELECT DISTINCT clique, clique FROM i UNION SELECT ur.x, ov.y FROM ur JOIN ov ON ur.y = ov.x), un AS (SELECT x AS clique, min(y) AS u FROM ur GROUP BY x)"""
BORDERS = """ru AS (SELECT DISTINCT rid, u FROM i JOIN un USING (clique)), rm AS (SELECT rid, count(*) AS m FROM ru GROUP BY rid), gs AS (SELECT comp, count(*) AS n_graph FROM comp GROUP BY comp),
bo AS (SELECT u, count(*) FILTER (m > 1) AS n_border, count(*) FILTER (m = 1) AS n_inner, max(n_graph) AS n_graph FROM ru JOIN rm USING (rid) JOIN comp USING (rid) JOIN gs USING (comp) GROUP BY u),
bv AS (SELECT *, n_border BETWEEN 1 AND 2 AND n_inner > 0 AND n_graph > n_border + n_inner AS violates FROM bo)"""

for _k in (1, 2):
    query(f"v_unions_k{_k}", f"{BASE}, {UNIONS.format(k=_k)} SELECT clique, u AS \"union\" FROM un")(lambda spark, sf, k=_k: C.v_unions(G.graph(listings(spark, sf)), k))


@query("borders_k2", f"{BASE}, {COMP}, {UNIONS.format(k=2)}, {BORDERS} SELECT u AS \"union\", n_border, n_inner, n_graph, violates FROM bv")
def borders_k2(spark, sf):
    i = G.graph(listings(spark, sf))
    return C.borders(i, C.v_unions(i, 2), G.record_components(i), 2)


@query("screen_round_1", f"{BASE}, {COMP}, {UNIONS.format(k=2)}, {BORDERS}, go AS (SELECT DISTINCT rid FROM ru JOIN rm USING (rid) JOIN bv USING (u) WHERE m > 1 AND violates) SELECT rid, clique FROM i WHERE rid NOT IN (SELECT rid FROM go)")
def screen_round_1(spark, sf):
    return C.screen_round(G.graph(listings(spark, sf)), 2)[0]


@query("cores_k0", f"{BASE}, {COMP} SELECT rid, comp AS core FROM comp")
def cores_k0(spark, sf):
    return C.find_cores(G.graph(listings(spark, sf)), 0)


for _k in (1, 2, 3, 4):
    query(f"cores_k{_k}")(lambda spark, sf, k=_k: C.find_cores(G.graph(listings(spark, sf)), k))
query("cores_screen_only")(lambda spark, sf: C.find_cores(G.graph(listings(spark, sf)), 2, "screen_only"))
query("core_metrics")(lambda spark, sf: C.find_cores(G.graph(listings(spark, sf)), 2, metrics=True))
query("agglomerative_cores")(lambda spark, sf: B.agglomerative_cores(listings(spark, sf)))


@query("cores_ladder_equal")
def cores_ladder_equal(spark, sf):
    """Strategies of the speed ladder against ``full``: records per strategy and those that differ (none)."""
    i = G.graph(listings(spark, sf, "p3_all"))
    full = materialise(C.find_cores(i, 2), "full")
    out = None
    for s in ("index", "sindex", "union", "full"):
        got = C.find_cores(i, 2, s)
        row = got.join(full.withColumnRenamed("core", "want"), "rid", "full").agg(F.count("core").alias("n_records"), F.count_if(~F.col("core").eqNullSafe(F.col("want"))).alias("n_differ")).withColumn("strategy", F.lit(s))
        out = row if out is None else out.unionByName(row)
    return out


# --- similarity ----------------------------------------------------------------------------------------------------


@query("signatures", f"{CONNECTED}, z AS (SELECT group_id, count(*) AS size FROM g GROUP BY group_id) SELECT group_id AS owner, attr, value, round(count(DISTINCT v.rid) / max(size)::DOUBLE, 6) AS weight FROM v JOIN g USING (rid) JOIN z USING (group_id) GROUP BY group_id, attr, value")
def signatures(spark, sf):
    r = listings(spark, sf)
    g = B.connected_graph(r).select(F.col("group_id").alias("owner"), "rid")
    return L.signatures(g, G.value_rows(r)).withColumn("weight", F.round("weight", 6))


@query("association_weights", f"""WITH {ctes()}, x AS (SELECT name AS owner, rid, value FROM v), sz AS (SELECT owner, count(DISTINCT rid) AS size FROM x GROUP BY owner), pop AS (SELECT owner, value, count(DISTINCT rid) / max(size)::DOUBLE AS pop FROM x JOIN sz USING (owner) GROUP BY ALL),
b AS (SELECT a.owner, a.value, o.value AS other, count(DISTINCT a.rid) AS n FROM x a JOIN x o ON a.owner = o.owner AND a.rid = o.rid AND a.value <> o.value GROUP BY ALL), via AS (SELECT b.owner, b.value, max(q.pop * (1 - 0.99::DOUBLE ** n)) AS via FROM b JOIN pop q ON q.owner = b.owner AND q.value = b.other GROUP BY ALL)
SELECT owner, value, round(greatest(pop, coalesce(via, 0.0::DOUBLE)), 6) AS weight FROM pop LEFT JOIN via USING (owner, value)""")
def association_weights(spark, sf):
    v = G.value_rows(listings(spark, sf)).select(F.col("name").alias("owner"), "rid", "value")
    return L.association_weights(v).withColumn("weight", F.round("weight", 6))


_SIG = f"{CONNECTED}, z AS (SELECT group_id, count(*) AS size FROM g GROUP BY group_id), sg AS (SELECT group_id, attr, value, count(DISTINCT v.rid) / max(size)::DOUBLE AS w FROM v JOIN g USING (rid) JOIN z USING (group_id) GROUP BY group_id, attr, value)"


@query("sim_dom", f"{_SIG} SELECT v.rid, group_id, round(1 - product(1 - 0.8::DOUBLE * w), 6) AS sim FROM v JOIN sg USING (attr, value) GROUP BY v.rid, group_id")
def sim_dom(spark, sf):
    """Noisy-or over all dominant values of a record with the popularity of its values in each group that has any of them."""
    r = listings(spark, sf)
    v = G.value_rows(r)
    s = L.signatures(B.connected_graph(r).select(F.col("group_id").alias("owner"), "rid"), v)
    left = F.exp(F.sum(F.log1p(-0.8 * F.col("weight"))))
    return v.join(s, ["attr", "value"]).groupBy("rid", F.col("owner").alias("group_id")).agg(F.round(1 - left, 6).alias("sim"))


@query("sim_com", f"{CONNECTED}, z AS (SELECT group_id, count(*) AS size FROM g GROUP BY group_id), n AS (SELECT group_id, name, count(*) / max(size)::DOUBLE AS w FROM r JOIN g USING (rid) JOIN z USING (group_id) GROUP BY ALL), q AS (SELECT group_id, sqrt(sum(w * w)) AS q FROM n GROUP BY group_id) SELECT rid, group_id, round(w / q, 6) AS sim FROM r JOIN n USING (name) JOIN q USING (group_id)")
def sim_com(spark, sf):
    """Weighted cosine of names between a record and the groups that hold its name."""
    r = listings(spark, sf)
    g = B.connected_graph(r).select(F.col("group_id").alias("owner"), "rid")
    s = L.signatures(g, r.select("rid", F.lit("name").alias("attr"), F.col("name").alias("value")))
    q = s.groupBy("owner").agg(F.sqrt(F.sum(F.col("weight") * F.col("weight"))).alias("q"))
    return r.select("rid", F.col("name").alias("value")).join(s, "value").join(q, "owner").select("rid", F.col("owner").alias("group_id"), F.round(F.col("weight") / F.col("q"), 6).alias("sim"))


@query("sim_multi", f"{CONNECTED}, z AS (SELECT group_id, count(*) AS size FROM g GROUP BY group_id), n AS (SELECT group_id, state, count(*) / max(size)::DOUBLE AS w FROM r JOIN g USING (rid) JOIN z USING (group_id) GROUP BY ALL) SELECT r.rid, g.group_id, round(w, 6) AS sim FROM r JOIN g USING (rid) JOIN n ON n.group_id = g.group_id AND n.state = r.state")
def sim_multi(spark, sf):
    """Share of a record's group that has its state."""
    r = listings(spark, sf)
    g = B.connected_graph(r).select(F.col("group_id").alias("owner"), "rid")
    s = L.signatures(g, r.select("rid", F.lit("state").alias("attr"), F.col("state").alias("value"))).drop("attr")
    return r.select("rid", F.col("state").alias("value")).join(g, "rid").join(s, ["owner", "value"]).select("rid", F.col("owner").alias("group_id"), F.round("weight", 6).alias("sim"))


@query("silhouette", f"{_SIG}, d AS (SELECT v.rid, group_id AS cluster, 1 - product(1 - 0.8::DOUBLE * w) AS sim FROM v JOIN sg USING (attr, value) GROUP BY ALL), m AS (SELECT rid, max(sim) FILTER (cluster = group_id) AS a, coalesce(max(sim) FILTER (cluster <> group_id), 0.0::DOUBLE) AS b FROM d JOIN g USING (rid) GROUP BY rid) SELECT rid AS eid, round(a, 6) AS a, round(b, 6) AS b, round((a - b + 0.01::DOUBLE) / (greatest(a, b) + 0.02::DOUBLE), 6) AS s FROM m")
def silhouette_rows(spark, sf):
    r = listings(spark, sf)
    v, g = G.value_rows(r), materialise(B.connected_graph(r), "groups")
    s = L.signatures(g.select(F.col("group_id").alias("owner"), "rid"), v)
    sims = v.join(s, ["attr", "value"]).groupBy("rid", "owner").agg((1 - F.exp(F.sum(F.log1p(-0.8 * F.col("weight"))))).alias("sim")).join(g, "rid")
    got = L.sv_index(sims.select(F.col("rid").alias("eid"), F.col("owner").alias("cluster"), (F.col("owner") == F.col("group_id")).alias("own"), "sim"))
    return got.select("eid", *[F.round(c, 6).alias(c) for c in "abs"])


_PAIRS_OF = "sum(n * (n - 1) / 2)"
query("learned_weights", f"""WITH RECURSIVE {ctes()}, sm AS (SELECT * FROM r WHERE gold IS NOT NULL ORDER BY md5(rid::VARCHAR || '|w'), rid LIMIT {SAMPLE}), d AS (SELECT DISTINCT name FROM sm WHERE name IS NOT NULL),
e AS (SELECT a.name AS x, b.name AS y FROM d a JOIN d b ON a.name = b.name OR jaro_winkler_similarity(a.name, b.name) > 0.8), reach(x, y) AS (SELECT x, y FROM e UNION SELECT reach.x, e.y FROM reach JOIN e ON reach.y = e.x),
bl AS (SELECT x AS name, min(y) AS block FROM reach GROUP BY x), w AS (SELECT block, gold, role, attr, value FROM (SELECT rid, 'com' AS role, 'name' AS attr, name AS value FROM sm UNION ALL SELECT rid, 'dom', 'phone', phone FROM sm UNION ALL SELECT rid, 'dom', 'url', url FROM sm) z JOIN sm USING (rid) JOIN bl USING (name) WHERE value IS NOT NULL),
ce AS (SELECT role, attr, value, block, gold, count(*) AS n FROM w GROUP BY ALL), ki AS (SELECT role, attr, value, CASE WHEN count(DISTINCT gold) = 1 THEN 'distinct' ELSE 'shared' END AS kind FROM ce GROUP BY ALL),
sa AS (SELECT role, kind, {_PAIRS_OF} AS b FROM ce JOIN ki USING (role, attr, value) GROUP BY ALL), ag AS (SELECT role, kind, {_PAIRS_OF} AS a FROM (SELECT role, attr, value, block, count(*) AS n FROM w GROUP BY ALL) JOIN ki USING (role, attr, value) GROUP BY ALL),
o1 AS (SELECT role, kind, b, a FROM sa JOIN ag USING (role, kind)), o AS (SELECT * FROM o1 UNION ALL SELECT role, 'all', sum(b), sum(a) FROM o1 GROUP BY role),
ev AS (SELECT role, {_PAIRS_OF} AS p FROM (SELECT role, attr, block, count(*) AS n FROM w GROUP BY ALL) GROUP BY role), gr AS (SELECT role, {_PAIRS_OF} AS g FROM (SELECT role, attr, block, gold, count(*) AS n FROM w GROUP BY ALL) GROUP BY role),
rt AS (SELECT role, (p - a - g + b + 1) / (p - a + 2) AS differ FROM o JOIN ev USING (role) JOIN gr USING (role) WHERE kind = 'all') SELECT role, kind, round((b + 1) / (a + 2), 6) AS agree, round(differ, 6) AS differ FROM o JOIN rt USING (role)""")(lambda spark, sf: L.learn_weights(r := listings(spark, sf), gold(r), SAMPLE).withColumns({c: F.round(c, 6) for c in ("agree", "differ")}))
query("blocks_exact", f"WITH {ctes()} SELECT rid, name AS block FROM r")(lambda spark, sf: L.blocks(listings(spark, sf), None))
query("blocks", f"WITH RECURSIVE k AS ({_similar(0.8)}), b AS (SELECT name, min(name) OVER (PARTITION BY class) AS block FROM k), {ctes()} SELECT rid, block FROM r JOIN b USING (name)")(lambda spark, sf: L.blocks(listings(spark, sf), 0.8))
query("block_stats", f"WITH {ctes()}, n AS (SELECT name, count(*) AS n FROM r GROUP BY name HAVING count(*) > 1) SELECT count(*) AS n_blocks, max(n) AS largest, round(avg(n), 6) AS mean_size, round(avg((n < 100)::INT), 6) AS below_100 FROM n")(lambda spark, sf: B.block_stats(L.blocks(listings(spark, sf), None)))

# --- clustering ----------------------------------------------------------------------------------------------------

for _v, _all in WHOLE.items():
    query(f"two_stage_{_v}")(lambda spark, sf, v=_all: method(spark, sf, v))
    query(f"two_stage_{_v}_exact_k1")(lambda spark, sf, v=_all: method(spark, sf, v, k=1, threshold=None))
query("core_only")(lambda spark, sf: L.two_stage(listings(spark, sf), stages="core_only"))
query("cluster_only")(lambda spark, sf: method(spark, sf, stages="cluster_only"))
for _i in ("greedy", "exhaustive"):
    query(f"initialise_{_i}")(lambda spark, sf, i=_i: method(spark, sf, settings=Settings(init=i, adjust=False)))
    query(f"cluster_{_i}")(lambda spark, sf, i=_i: method(spark, sf, settings=Settings(init=i)))

# --- baselines and measures ------------------------------------------------------------------------------------------

query("same_name", f"WITH {ctes()}, {SAME} SELECT * FROM g")(lambda spark, sf: B.same_name(listings(spark, sf)))
_SAME95 = f"WITH RECURSIVE k AS ({_similar(0.95)}), {ctes()}, g AS (SELECT rid, coalesce(min(rid) OVER (PARTITION BY class), rid) AS group_id FROM r JOIN k USING (name))"
query("same_name_95", f"{_SAME95} SELECT * FROM g")(lambda spark, sf: B.same_name(listings(spark, sf), L.NAME))
query("connected_graph", f"{CONNECTED} SELECT * FROM g")(lambda spark, sf: B.connected_graph(listings(spark, sf)))
_EDGE = f"WITH RECURSIVE {ctes()}, {PAIRS}, e AS (SELECT r1 AS x, r2 AS y FROM ps WHERE sim > 0.8 UNION SELECT r2, r1 FROM ps WHERE sim > 0.8), reach(x, y) AS (SELECT x, x FROM e UNION SELECT reach.x, e.y FROM reach JOIN e ON reach.y = e.x), cm AS (SELECT x AS rid, min(y) AS comp FROM reach GROUP BY x), g AS (SELECT r.rid, coalesce(comp, r.rid) AS group_id FROM r LEFT JOIN cm USING (rid))"
query("edge_partition", f"{_EDGE} SELECT * FROM g")(lambda spark, sf: B.edge_partition(listings(spark, sf)))
query("edge_center")(lambda spark, sf: B.edge_star(listings(spark, sf)))
query("edge_merge")(lambda spark, sf: B.edge_star(listings(spark, sf), merge=True))
_MATCH = f"WITH RECURSIVE k AS ({_similar(0.95)}), {ctes()}, {clique_ctes("SELECT DISTINCT rid, concat_ws('|', class, attr, value) AS clique FROM v JOIN k USING (name)")}, {COMP} SELECT r.rid, coalesce(comp, r.rid) AS group_id FROM r LEFT JOIN comp USING (rid)"
query("match_merge", _MATCH)(lambda spark, sf: B._all(r := listings(spark, sf), G.record_components(G.graph(r, 0.95))))
query("strict_all_attributes", f"WITH {ctes()} SELECT rid, min(rid) OVER (PARTITION BY name, phone, url, url2, state, category) AS group_id FROM r")(lambda spark, sf: B.strict_rule(listings(spark, sf)))
query("tfidf_weights", f"WITH {ctes()}, {FEATURES} SELECT feature, round(ln((SELECT count(*) FROM r) / count(*)::DOUBLE), 6) AS idf FROM f GROUP BY feature")(lambda spark, sf: (lambda r: B.features(r).groupBy("feature").agg(F.round(F.log(F.lit(float(r.count())) / F.count("*")), 6).alias("idf")))(listings(spark, sf)))
_CORE0 = f"{BASE}, {COMP}, {FEATURES}"
query("tfidf_assign", f"""{_CORE0}, sz AS (SELECT comp, count(*) AS size FROM comp GROUP BY comp), idf AS (SELECT feature, ln((SELECT count(*) FROM r) / count(*)::DOUBLE) AS idf FROM f GROUP BY feature),
w AS (SELECT comp, feature, count(*) / max(size)::DOUBLE * max(idf) * max(idf) AS w FROM f JOIN comp USING (rid) JOIN sz USING (comp) JOIN idf USING (feature) GROUP BY comp, feature), sc AS (SELECT rid, comp, round(sum(w), 9) AS score FROM f JOIN w USING (feature) WHERE rid NOT IN (SELECT rid FROM comp) GROUP BY ALL HAVING round(sum(w), 9) > 0),
b AS (SELECT rid, comp FROM sc QUALIFY row_number() OVER (PARTITION BY rid ORDER BY score DESC, comp) = 1), q AS (SELECT * FROM comp UNION ALL SELECT * FROM b) SELECT r.rid, coalesce(comp, r.rid) AS group_id FROM r LEFT JOIN q USING (rid)""")(lambda spark, sf: B.tfidf_assign(r := listings(spark, sf), C.find_cores(G.graph(r), 0)))
query("vote_assign_round", f"{_CORE0}, rep AS (SELECT comp, feature FROM f JOIN comp USING (rid) GROUP BY ALL HAVING count(*) >= 5), vo AS (SELECT rid, comp, count(*) AS votes FROM f JOIN rep USING (feature) WHERE rid NOT IN (SELECT rid FROM comp) GROUP BY ALL) SELECT rid, comp AS core FROM vo QUALIFY row_number() OVER (PARTITION BY rid ORDER BY votes DESC, comp) = 1")(lambda spark, sf: B.vote_round(r := listings(spark, sf), C.find_cores(G.graph(r), 0)))
query("vote_assign")(lambda spark, sf: B.vote_assign(r := listings(spark, sf), method_cores(r)))
query("tfidf_two_stage")(lambda spark, sf: B.tfidf_assign(r := listings(spark, sf), B.agglomerative_cores(r)))

query("prf_same_name", f"WITH {ctes()}, {SAME}, {PRF}")(lambda spark, sf: B.pairwise_prf(B.same_name(r := listings(spark, sf)), gold(r)))
query("prf_same_name_95", f"{_SAME95}, {PRF}")(lambda spark, sf: B.pairwise_prf(B.same_name(r := listings(spark, sf), L.NAME), gold(r)))
query("prf_connected", f"{CONNECTED}, {PRF}")(lambda spark, sf: B.pairwise_prf(B.connected_graph(r := listings(spark, sf)), gold(r)))
query("prf_edge_partition", f"{_EDGE}, {PRF}")(lambda spark, sf: B.pairwise_prf(B.edge_partition(r := listings(spark, sf)), gold(r)))
query("prf_two_stage")(lambda spark, sf: B.pairwise_prf(method(spark, sf), gold(listings(spark, sf))))
_PROFILE = "pf AS (SELECT group_id, count(*) AS n_records, count(DISTINCT name) AS n_names, count(DISTINCT phone) AS n_phones, count(DISTINCT category) AS n_categories FROM r JOIN g USING (rid) GROUP BY group_id), ul AS (SELECT group_id, count(DISTINCT u) AS n_urls FROM (SELECT rid, url AS u FROM r UNION ALL SELECT rid, url2 FROM r) JOIN g USING (rid) GROUP BY group_id)"
query("group_profile", f"{CONNECTED}, {_PROFILE} SELECT group_id, n_records, n_names, n_phones, coalesce(n_urls, 0) AS n_urls, n_categories FROM pf LEFT JOIN ul USING (group_id)")(lambda spark, sf: B.group_profile(r := listings(spark, sf), B.connected_graph(r)))
query("top5_groups", f"{CONNECTED}, {_PROFILE} SELECT group_id, n_records, n_names, n_phones, coalesce(n_urls, 0) AS n_urls, n_categories FROM pf LEFT JOIN ul USING (group_id) ORDER BY n_records DESC, group_id LIMIT 5")(lambda spark, sf: B.group_profile(r := listings(spark, sf), B.connected_graph(r)).orderBy(F.desc("n_records"), "group_id").limit(5))

# --- workloads: one row of accuracy per variant -------------------------------------------------------------------


def compare(spark, runs) -> DataFrame:
    """variant, tp, fp, fn, precision, recall, f for (variant, groups, records)."""
    out = None
    for name, groups, r in runs:
        row = B.pairwise_prf(materialise(groups, "groups"), gold(r)).withColumn("variant", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


def _sweep(view: str, variants: dict):
    """Variants are functions of the records and the learned weights, or settings for the second stage over cores that are found once.

    Settings run with learned weights, unless they name others; weights alone run with the other settings as they are.
    A dictionary holds options of the whole method. The records' close names are found once for all of these.
    A tuple holds a function that finds other cores for the second stage."""

    def run(spark, sf):
        r = materialise(listings(spark, sf, view), "listings")
        weights, pairs, packed, runs = learned(spark, sf, view, records=r), None, None, []
        for name, f in variants.items():
            if isinstance(f, (Settings, Weights, tuple, dict)) and pairs is None:
                pairs = L.close_names(r)
            if isinstance(f, (Settings, Weights)) and packed is None:
                packed = L.pack(r, C.find_cores(G.graph(r, L.NAME, pairs), L.ROBUST), L.CLOSE, pairs)
            if isinstance(f, Weights):
                runs.append((name, L.assign(packed, Settings(weights=f)), r))
            elif isinstance(f, tuple):
                runs.append((name, L.assign(L.pack(r, f[0](r), L.CLOSE, pairs), Settings(weights=weights)), r))
            elif isinstance(f, Settings):
                runs.append((name, L.assign(packed, f.but(weights=weights) if f.weights == Weights() else f), r))
            elif isinstance(f, dict):
                known = pairs if f.get("threshold") is None or f["threshold"] >= L.CLOSE else None
                runs.append((name, L.two_stage(r, settings=Settings(weights=weights), pairs=known, **f), r))
            elif isinstance(f, str):
                runs.append((name, L.assign(packed, Settings(weights=learned(spark, sf, view, f, r))), r))
            else:
                runs.append((name, f(r, weights), r))
        return compare(spark, runs)

    return run


def _two(**how) -> dict:
    """The whole method with other options."""
    return how


def _one(f):
    """A method without weights."""
    return lambda r, w: f(r)


def _after(f):
    """The second stage over other cores."""
    return (f,)


def _set(**changes) -> Settings:
    return Settings().but(**changes)


#: One-stage methods that compare records, of which the best stands for all.
ONE_STAGE = {"edge_partition": lambda r, e: B.edge_partition(r, edges=e), "edge_center": lambda r, e: B.edge_star(r, edges=e), "edge_merge": lambda r, e: B.edge_star(r, merge=True, edges=e)}


def _overall(view: str, names=None):
    """All methods on one set; the names' and the records' similarities are computed once for all."""

    def run(spark, sf):
        r = materialise(listings(spark, sf, view), "listings")
        edges = B.alike(r)
        runs = [(name, f(r, edges), r) for name, f in ONE_STAGE.items()]
        if names is None:
            pairs = L.close_names(r)
            packed = L.pack(r, C.find_cores(G.graph(r, L.NAME, pairs), L.ROBUST), L.CLOSE, pairs)
            classes = G.name_classes(r, L.NAME, pairs)
            runs += [("same_name", B.same_name(r, classes=classes), r), ("same_name_exact", B.same_name(r), r), ("connected_graph", B.connected_graph(r), r)]
            runs += [("tfidf_two_stage", B.tfidf_assign(r, B.agglomerative_cores(r, edges=edges)), r), ("two_stage", L.assign(packed, Settings(weights=learned(spark, sf, view, records=r))), r)]
        return compare(spark, runs)

    return run


for _v, _all in WHOLE.items():
    query(f"overall_{_v}")(_overall(_all))


@query("best_one_stage")
def best_one_stage(spark, sf):
    """The one-stage method with the best F on each planted set."""
    out = None
    for name, view in WHOLE.items():
        best = _overall(view, ONE_STAGE)(spark, sf).orderBy(F.desc("f"), "variant").limit(1).withColumn("view", F.lit(name))
        out = best if out is None else out.unionByName(best)
    return out


def _similar_edges(r: DataFrame) -> DataFrame:
    """Cores over edges of high similarity of all attributes but the location; each edge is a clique."""
    e = B.weighted_pairs(r)
    return C.find_cores(e.select(F.explode(F.array("r1", "r2")).alias("rid"), F.concat_ws("-", F.col("r1").cast("string"), F.col("r2").cast("string")).alias("clique")), L.ROBUST)


query("ablation_stages")(_sweep("p1", {"both": Settings(), "core_only": _two(stages="core_only"), "cluster_only": _two(stages="cluster_only")}))
query("ablation_core_strategy")(_sweep("p4p_all", {"full": Settings(), "screen_only": _two(strategy="screen_only"), "agglomerative": _after(B.agglomerative_cores)}))
query("ablation_edge_rule")(_sweep("p1", {"one_dominant": Settings(), "two_dominant": _after(lambda r: C.find_cores(G.two_dominant_cliques(G.value_rows(classed(r))), L.ROBUST)), "similarity": _after(_similar_edges)}))
query("sweep_k")(_sweep("p1", {f"k{k}": _two(k=k) for k in range(5)}))
query("sweep_p")(_sweep("p1", {f"p{p}": _set(p=p) for p in (0.8, 0.9, 1.0)}))
query("sweep_theta")(_sweep("p1", {f"theta{t}": _set(theta=t) for t in (0.5, 0.6, 0.7)}))
query("sweep_name")(_sweep("p1", {"exact": _two(threshold=None)} | {f"name{t}": _two(threshold=t) for t in (0.8, 0.9, 0.95)}))
query("ablation_second_stage")(_sweep("p1", {"clustering": Settings(), "vote": _one(lambda r: B.vote_assign(r, method_cores(r))), "tfidf": _one(lambda r: B.tfidf_assign(r, method_cores(r)))}))
query("ablation_clustering")(_sweep("p1", {f"{i}_{a}": _set(init=i, adjust=a == "adjust") for i in ("greedy", "exhaustive") for a in ("adjust", "plain")}))
query("ablation_value_weight")(_sweep("p1", {w: _set(value_weight=w) for w in ("popularity", "none")}))
query("ablation_value_weight_p4p")(_sweep("p4p_all", {w: _set(value_weight=w) for w in ("popularity", "none")}))
query("ablation_dominant")(_sweep("p1", {d: _set(dominant=d) for d in ("united", "separated")}))
query("ablation_weights")(_sweep("p1", {"double": Settings(), "single": "single"}))
query("ablation_presets")(_sweep("p1", {"learned": Settings()} | PRESETS))


def _without(*columns):
    return lambda r, w: L.two_stage(r.withColumns({c: F.lit(None).cast("string") for c in columns}), settings=Settings(weights=w))


query("ablation_attributes")(_sweep("p4p_all", {"name": _without("phone", "url", "url2", "state", "category"), "dominant": _without("state", "category"), "category": _without("state"), "state": _without("category"), "all": Settings()}))


@query("ladder_fifths")
def ladder_fifths(spark, sf):
    """Graph and core sizes on growing fifths of the order-based listings: rows grow in proportion."""
    r = materialise(listings(spark, sf, "n2").withColumn("fifth", F.pmod(F.xxhash64("rid"), F.lit(5))), "fifths")
    out = None
    for n in range(1, 6):
        i = G.graph(r.where(F.col("fifth") < n))
        row = i.agg(F.lit(n * 20).alias("percent"), F.count("*").alias("incidences"), F.countDistinct("clique").alias("cliques")).crossJoin(C.find_cores(i, 2).agg(F.count("*").alias("core_records"), F.countDistinct("core").alias("cores")))
        out = row if out is None else out.unionByName(row)
    return out


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Groups of the random-chains view by the whole method."""
    return method(spark, sf_dir)


