"""URL filter by empirical-Bayes host reputation, in DataFrame operations only.

Outcomes of labelled pages are counted by host, registered domain and suffix. Each level is a
beta-binomial around the mean of the level above; one concentration per level comes from the
moments of all its members. A host is blocked when a lower bound of its posterior bad rate
exceeds a threshold; explicit (host, path) rules go before that.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower

#: Second-level labels that, under a two-letter suffix, belong to the suffix. Fixed values.
SECOND_LEVEL = ("ac", "co", "com", "edu", "gov", "net", "org")
#: Rules (verdict, host, path).
RULES = (("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/"))
Z, MAX_BAD, MIN_RHO, MAX_RHO = 1.645, 0.25, 0.001, 0.9


def split_url(url: Column) -> tuple[Column, Column]:
    """Host and path as in the contract: null or no ``://`` gives two empty strings."""
    at = F.instr(url, "://")
    rest = F.substr(url, at + F.lit(3))
    found = F.coalesce(at, F.lit(0)) > 0
    host = ascii_lower(F.regexp_extract(rest, r"^[^/?#]*", 0))
    return F.when(found, host).otherwise(""), F.when(found, F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)).otherwise("")


def with_domain(hosts: DataFrame) -> DataFrame:
    """Add ``suffix`` and ``domain`` (suffix and one label more) to a frame with ``host``."""
    parts = F.split(F.col("host"), r"\.")
    deep = (F.size(parts) > 2) & (F.length(F.element_at(parts, -1)) == 2) & F.try_element_at(parts, F.lit(-2)).isin(*SECOND_LEVEL)
    k = F.when(deep, 2).otherwise(1)
    return hosts.withColumns({"suffix": F.substring_index("host", ".", -1), "domain": F.substring_index("host", ".", -2)}).withColumns(
        {"suffix": F.when(k == 2, F.substring_index("host", ".", -2)).otherwise(F.col("suffix")), "domain": F.when(k == 2, F.substring_index("host", ".", -3)).otherwise(F.col("domain"))}
    )


def _strength(spread: Column, within: Column, units: Column, parents: Column, n: Column, sq: Column, p: Column) -> Column:
    """Concentration of a beta-binomial from moments: members' squared deviations against binomial noise."""
    free = units - parents
    noise = p * (1 - p)
    rho = (spread - within - noise * free) / (noise * (n - sq - free))
    rho = F.when((noise <= 0) | (n - sq - free <= 0) | (free <= 0), MIN_RHO).otherwise(F.greatest(F.lit(MIN_RHO), F.least(F.lit(MAX_RHO), rho)))
    return 1 / rho - 1


def host_reputation(labelled: DataFrame, z: float = Z) -> DataFrame:
    """``labelled(host, bad)`` (bad 0/1, null for pages without outcome) -> host, domain, suffix, n, bad_rate, bound.

    Sums are pre-aggregated by host first, so a host with a third of all pages is one row afterwards. A host without
    outcomes has the prior of its domain, else of its suffix, else the global one; without any outcome at all, nulls.
    """
    every = with_domain(labelled.groupBy("host").agg(F.count("bad").alias("n"), F.coalesce(F.sum("bad"), F.lit(0)).cast("long").alias("k")))
    h = every.where("n > 0")
    d = h.groupBy("suffix", "domain").agg(F.sum("n").alias("dn"), F.sum("k").alias("dk"), F.sum(F.col("k") * F.col("k") / F.col("n")).alias("dss"), F.sum(F.col("n") * F.col("n")).alias("dsq"), F.count("*").alias("dh"))
    s = d.groupBy("suffix").agg(F.sum("dn").alias("sn"), F.sum("dk").alias("sk"))
    t = d.agg(F.sum("dn").alias("gn"), F.sum("dk").alias("gk"), F.sum("dss").alias("hss"), F.sum(F.col("dsq") / F.col("dn")).alias("hsq"), F.sum("dh").alias("nh"), F.sum(F.col("dk") * F.col("dk") / F.col("dn")).alias("ds"), F.count("*").alias("nd"))
    x = d.join(s, "suffix").groupBy("suffix", "sn", "sk").agg(F.sum(F.col("dn") * F.col("dn")).alias("q"))
    u = x.agg(F.sum(F.col("q") / F.col("sn")).alias("dq"), F.sum(F.col("sk") * F.col("sk") / F.col("sn")).alias("ss"), F.count("*").alias("ns"), F.sum(F.col("sn") * F.col("sn")).alias("sq"))
    p = F.col("gk") / F.col("gn")
    g = t.crossJoin(u).select(  # one row each
        ((F.col("gk") + 0.5) / (F.col("gn") + 1)).alias("p0"),
        _strength(F.col("ss"), F.col("gk") * F.col("gk") / F.col("gn"), F.col("ns"), F.lit(1), F.col("gn"), F.col("sq") / F.col("gn"), p).alias("ms"),
        _strength(F.col("ds"), F.col("ss"), F.col("nd"), F.col("ns"), F.col("gn"), F.col("dq"), p).alias("md"),
        _strength(F.col("hss"), F.col("ds"), F.col("nh"), F.col("nd"), F.col("gn"), F.col("hsq"), p).alias("mh"),
    )
    by_suffix = s.crossJoin(F.broadcast(g)).select("suffix", "md", ((F.col("sk") + F.col("ms") * F.col("p0")) / (F.col("sn") + F.col("ms"))).alias("suffix_rate"))
    by_domain = d.join(by_suffix, "suffix").select("suffix", "domain", ((F.col("dk") + F.col("md") * F.col("suffix_rate")) / (F.col("dn") + F.col("md"))).alias("domain_rate"))
    known = every.join(by_domain, ["suffix", "domain"], "left").join(by_suffix.drop("md"), "suffix", "left").crossJoin(F.broadcast(g))
    prior = F.coalesce("domain_rate", "suffix_rate", "p0")
    a, b = F.col("k") + F.col("mh") * prior, F.col("n") - F.col("k") + F.col("mh") * (1 - prior)
    mean = a / (a + b)
    return known.select("host", "domain", "suffix", "n", mean.alias("bad_rate"), (mean - z * F.sqrt(a * b / ((a + b) * (a + b) * (a + b + 1)))).alias("bound"))


def match_rule(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """The longest rule that fits (host or a parent of it, path prefix) and its verdict; nulls where none does."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for kind, h, p in sorted(rules, key=lambda r: (len(r[1] + r[2]), r[1:])):  # the longest is tried first: it is the outermost
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        rule, verdict = F.when(fits, h + p).otherwise(rule), F.when(fits, kind).otherwise(verdict)
    return rule, verdict


def judge_urls(pages: DataFrame, outcomes: DataFrame, rules=RULES, z: float = Z, max_bad: float = MAX_BAD, inherit: bool = True) -> DataFrame:
    """``pages(page_id, url)`` and ``outcomes(page_id, bad)`` -> page_id, host, path, rule, verdict, bad_bound.

    Rows stay one to one with ``pages`` (repeated ones too). A page with several outcomes counts its worst;
    null ids never match an outcome. Without any outcome, bounds are null and pages without rule are allowed; unless
    ``inherit``, so are those of each host that has no outcome of its own.
    """
    host, path = split_url(F.col("url"))
    p = pages.select("page_id", host.alias("host"), path.alias("path"))
    seen = outcomes.groupBy("page_id").agg(F.max("bad").alias("bad"))
    rep = host_reputation(p.join(seen, "page_id", "left").select("host", "bad"), z).where(F.lit(inherit) | (F.col("n") > 0)).select("host", "bound")
    rule, verdict = match_rule(F.col("host"), F.col("path"), rules)
    own = F.when(F.col("bound") > max_bad, "block").otherwise("allow")
    return p.join(rep, "host", "left").select("page_id", "host", "path", rule.alias("rule"), F.coalesce(verdict, own).alias("verdict"), F.round("bound", 6).alias("bad_bound"))
