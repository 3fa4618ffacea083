"""Queries over the tables of the text operators, and their SQL where SQL can say it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat, decontaminate, mixing, neighbours, quality, simhash, suffixes, tokens, toxicity, urls
from .common import table


def op8_url_reputation(spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = table(spark, sf_dir, "labels").select(F.col("doc_id").alias("page_id"), (1 - F.col("quality")).alias("bad"))
    return urls.judge_urls(table(spark, sf_dir, "pages"), labels, inherit=False)


def op9_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    m = mixing.with_copies(table(spark, sf_dir, "documents").select("doc_id", "text", "source"))
    return m.select("doc_id", F.col("_size").alias("size"), F.col("_source_size").alias("source_size"), F.col("_target").alias("target"), (F.col("_size") * F.col("_copies")).cast("long").alias("taken"))


def op10_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark").select("item_id", "text"))


def op5_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = simhash.near_components(table(spark, sf_dir, "documents"), k=3)
    return d.select("doc_id", simhash.hex16(F.col("fp")).alias("fingerprint"), "component_id")


def tokenizer_file(name: str) -> str:
    """Where the installed tokenizer files lie."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokens.token_counts(table(spark, sf_dir, "documents"), tokenizer_file("piece_bpe_32k.model"))


def op4_multiprobe_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = table(spark, sf_dir, "embeddings")
    return neighbours.search(v, v.where("vec_id % 50 = 0"))


def op7_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.formatted_corpus(table(spark, sf_dir, "conversations"), tokenizer_file("byte_bpe_50k.json"))


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return toxicity.scores(docs, *toxicity.fit(docs, table(spark, sf_dir, "labels")))


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    s = quality.score(docs, quality.fit(docs, table(spark, sf_dir, "labels")))
    return s.select("doc_id", F.col("_expected").alias("expected_grade"), F.col("_tail").alias("tail_probability"), (F.col("_tail") >= 0.5).alias("keep"))


def op3_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffixes.report(table(spark, sf_dir, "documents"))


QUERIES = {"op1_toxicity": op1_toxicity, "op2_quality": op2_quality, "op3_suffix_dedup": op3_suffix_dedup, "op4_multiprobe_neighbours": op4_multiprobe_neighbours, "op7_chat_format": op7_chat_format, "op5_simhash": op5_simhash, "op6_token_counts": op6_token_counts, "op8_url_reputation": op8_url_reputation, "op9_mix_sources": op9_mix_sources, "op10_decontaminate": op10_decontaminate}

_UP, _LOW = "'ABCDEFGHIJKLMNOPQRSTUVWXYZ'", "'abcdefghijklmnopqrstuvwxyz'"

SQL_8 = rf"""
WITH p0 AS (SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
p AS (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*', 0), {_UP}, {_LOW}) AS host,
  regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM p0),
o AS (SELECT doc_id AS page_id, max(1 - quality) AS bad FROM labels GROUP BY 1),
h0 AS (SELECT host, count(*) AS n, sum(bad) AS k, string_split(host, '.') AS parts FROM p JOIN o USING (page_id) WHERE bad IS NOT NULL GROUP BY host),
h1 AS (SELECT *, CASE WHEN len(parts) > 2 AND length(parts[-1]) = 2 AND parts[-2] IN ('ac','co','com','edu','gov','net','org') THEN 2 ELSE 1 END AS deep FROM h0),
h AS (SELECT host, n, k, array_to_string(parts[-deep:], '.') AS suffix, array_to_string(parts[-(deep + 1):], '.') AS domain FROM h1),
d AS (SELECT suffix, domain, sum(n) AS dn, sum(k) AS dk, sum(k * k / n::DOUBLE) AS dss, sum(n * n) AS dsq, count(*) AS dh FROM h GROUP BY ALL),
s AS (SELECT suffix, sum(dn) AS sn, sum(dk) AS sk, sum(dn * dn) AS q FROM d GROUP BY ALL),
t AS (SELECT sum(dn) AS gn, sum(dk) AS gk, sum(dss) AS hss, sum(dsq / dn::DOUBLE) AS hsq, sum(dh) AS nh, sum(dk * dk / dn::DOUBLE) AS ds, count(*) AS nd FROM d),
u AS (SELECT sum(q / sn::DOUBLE) AS dq, sum(sk * sk / sn::DOUBLE) AS ss, count(*) AS ns, sum(sn * sn) AS sq FROM s),
v AS (SELECT (gk + 0.5::DOUBLE) / (gn + 1) AS p0, gk / gn::DOUBLE * (1 - gk / gn::DOUBLE) AS noise, * FROM t, u),
w AS (SELECT p0,
  CASE WHEN noise <= 0 OR gn - sq / gn::DOUBLE - (ns - 1) <= 0 OR ns - 1 <= 0 THEN 0.001::DOUBLE ELSE greatest(0.001::DOUBLE, least(0.9::DOUBLE, (ss - gk * gk / gn::DOUBLE - noise * (ns - 1)) / (noise * (gn - sq / gn::DOUBLE - (ns - 1))))) END AS rs,
  CASE WHEN noise <= 0 OR gn - dq - (nd - ns) <= 0 OR nd - ns <= 0 THEN 0.001::DOUBLE ELSE greatest(0.001::DOUBLE, least(0.9::DOUBLE, (ds - ss - noise * (nd - ns)) / (noise * (gn - dq - (nd - ns))))) END AS rd,
  CASE WHEN noise <= 0 OR gn - hsq - (nh - nd) <= 0 OR nh - nd <= 0 THEN 0.001::DOUBLE ELSE greatest(0.001::DOUBLE, least(0.9::DOUBLE, (hss - ds - noise * (nh - nd)) / (noise * (gn - hsq - (nh - nd))))) END AS rh
  FROM v),
g AS (SELECT p0, 1 / rs - 1 AS ms, 1 / rd - 1 AS md, 1 / rh - 1 AS mh FROM w),
dr AS (SELECT d.suffix, d.domain, mh, (dk + md * ((sk + ms * p0) / (sn + ms))) / (dn + md) AS rate FROM d JOIN s USING (suffix), g),
ab AS (SELECT host, k + mh * rate AS a, n - k + mh * (1 - rate) AS b FROM h JOIN dr USING (suffix, domain)),
r AS (SELECT host, a / (a + b) - 1.645::DOUBLE * sqrt(a * b / ((a + b) * (a + b) * (a + b + 1))) AS bound FROM ab),
rules(verdict, rhost, rpath) AS (VALUES ('block','net','/'), ('allow','example.net','/en/'), ('block','example.com','/de/'), ('allow','org','/fr/')),
fit AS (SELECT DISTINCT host, path, first_value(rhost || rpath) OVER f AS rule, first_value(verdict) OVER f AS verdict
  FROM (SELECT DISTINCT host, path FROM p) JOIN rules ON (host = rhost OR ends_with(host, '.' || rhost)) AND starts_with(path, rpath)
  WINDOW f AS (PARTITION BY host, path ORDER BY length(rhost || rpath) DESC))
SELECT p.page_id, p.host, p.path, fit.rule, coalesce(fit.verdict, CASE WHEN r.bound > 0.25 THEN 'block' ELSE 'allow' END) AS verdict, round(r.bound, 6) AS bad_bound
FROM p LEFT JOIN r USING (host) LEFT JOIN fit ON fit.host = p.host AND fit.path = p.path
"""

SQL_9 = r"""
WITH d AS (SELECT doc_id, source, CASE WHEN text IS NULL THEN 0 ELSE len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')) END AS size,
  ((coalesce(doc_id, 0) % 256) + 256) % 256 AS chunk FROM documents),
s0 AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
s1 AS (SELECT *, CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 WHEN 0 THEN 3 WHEN 1 THEN 1 ELSE 2 END AS weight, source_size * 2 AS cap FROM s0),
s2 AS (SELECT *, (1.5::DOUBLE * sum(source_size) OVER () - (sum(cap) OVER (ORDER BY cap / weight::DOUBLE, source NULLS LAST ROWS UNBOUNDED PRECEDING) - cap))
  / sum(weight) OVER (ORDER BY cap / weight::DOUBLE, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM s1),
s3 AS (SELECT *, max(CASE WHEN level * weight <= cap THEN level END) OVER () AS lv FROM s2),
s AS (SELECT source, source_size, CASE WHEN lv IS NULL THEN cap::DOUBLE ELSE least(cap::DOUBLE, lv * weight) END AS target,
  ('0x' || substr(md5(coalesce(source, '') || '|mix-1'), 1, 7))::BIGINT / (16::DOUBLE ** 7) AS u FROM s3),
e AS (SELECT d.doc_id, d.size, s.source_size, s.target, s.u, CASE WHEN s.source_size > 0 THEN s.target / s.source_size ELSE 0.0::DOUBLE END AS ratio,
  row_number() OVER (PARTITION BY d.source ORDER BY d.size, d.chunk, d.doc_id) AS pos FROM d JOIN s ON d.source IS NOT DISTINCT FROM s.source)
SELECT doc_id, size::BIGINT AS size, source_size, target, (size * (floor(pos * ratio + u) - floor((pos - 1) * ratio + u)))::BIGINT AS taken FROM e
"""

_NORM = rf"translate(text, {_UP}, {_LOW})"
_WORDS = r"'[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'"
SQL_10 = rf"""
WITH b AS (SELECT item_id, regexp_extract_all({_NORM}, {_WORDS}) AS w FROM benchmark WHERE text IS NOT NULL),
g AS (SELECT DISTINCT item_id, least(len(w), 10) AS m, unnest(list_transform(range(1, len(w) - least(len(w), 10) + 2), lambda i: array_to_string(w[i:i + least(len(w), 10) - 1], ' '))) AS win FROM b WHERE len(w) > 0),
m AS (SELECT DISTINCT m FROM g),
d AS (SELECT rowid AS rid, doc_id, CASE WHEN text IS NULL THEN [] ELSE regexp_extract_all({_NORM}, {_WORDS}) END AS w FROM (SELECT row_number() OVER () AS rowid, * FROM documents)),
x AS (SELECT rid, m, unnest(range(1, len(w) - m + 2)) AS i, unnest(list_transform(range(1, len(w) - m + 2), lambda i: array_to_string(w[i:i + m - 1], ' '))) AS win FROM d, m),
hit AS (SELECT x.rid, x.i, g.m, g.item_id FROM x JOIN g ON x.win = g.win AND x.m = g.m),
n AS (SELECT rid, count(DISTINCT pos) AS n_hit FROM (SELECT DISTINCT rid, unnest(range(i, i + m)) AS pos FROM hit) GROUP BY rid),
it AS (SELECT rid, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT rid, item_id::VARCHAR AS item FROM hit) GROUP BY rid)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items, sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN n USING (rid) LEFT JOIN it USING (rid)
"""

ORACLES = {"op8_url_reputation": SQL_8, "op9_mix_sources": SQL_9, "op10_decontaminate": SQL_10}
