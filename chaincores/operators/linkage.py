"""The second stage and the whole method: cores and satellites to groups."""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from ..plans.cluster import Element, Settings, Weights, cluster_block
from ..session import dealt, materialise
from .cores import find_cores
from .graph import graph, name_classes, record_components, similar_pairs

ALIKE = 0.9
#: The method's edge rule and cores: name similarity above this, and the records that a core may lose.
NAME, ROBUST = 0.95, 2
#: Names in one block are more similar than this.
CLOSE = 0.8


def elements(records: DataFrame, cores: DataFrame) -> DataFrame:
    """rid, eid, is_core: a core's smallest record names it; every other record is a satellite of its own."""
    return records.select("rid").join(cores, "rid", "left").select("rid", F.coalesce("core", "rid").alias("eid"), F.col("core").isNotNull().alias("is_core"))


def close_names(records: DataFrame, threshold: float = CLOSE) -> DataFrame:
    """All pairs of names above the least threshold that any step asks for: found once."""
    return materialise(similar_pairs(records, threshold), "names")


def blocks(records: DataFrame, threshold: float | None = CLOSE, pairs: DataFrame | None = None) -> DataFrame:
    """rid, block: records whose names are close, closed transitively; null names are blocks of their own."""
    c = name_classes(records, threshold, pairs)
    b = c.groupBy("class").agg(F.min("name").alias("block")).join(c, "class").select("name", "block")
    return records.select("rid", "name").join(b, "name", "left").select("rid", F.coalesce("block", F.concat(F.lit("#"), F.col("rid").cast("string"))).alias("block"))


def signatures(members: DataFrame, values: DataFrame) -> DataFrame:
    """``members(owner, rid)``, ``values(rid, attr, value)`` -> owner, attr, value, weight: share of the owner's records."""
    size = members.groupBy("owner").agg(F.countDistinct("rid").alias("size"))
    held = members.join(values.select("rid", "attr", "value"), "rid").groupBy("owner", "attr", "value").agg(F.countDistinct("rid").alias("n"))
    return held.join(size, "owner").select("owner", "attr", "value", (F.col("n") / F.col("size")).alias("weight"))


def association_weights(values: DataFrame, epsilon: float = 0.99) -> DataFrame:
    """``values(owner, rid, value)`` -> owner, value, weight: the larger of popularity and the best popularity of a companion,
    discounted by how rarely the two occur together."""
    size = values.groupBy("owner").agg(F.countDistinct("rid").alias("size"))
    pop = values.groupBy("owner", "value").agg(F.countDistinct("rid").alias("n")).join(size, "owner").withColumn("pop", F.col("n") / F.col("size"))
    o = values.select("owner", "rid", F.col("value").alias("other"))
    both = values.join(o, ["owner", "rid"]).where("value <> other").groupBy("owner", "value", "other").agg(F.countDistinct("rid").alias("c"))
    via = both.join(pop.select("owner", F.col("value").alias("other"), F.col("pop").alias("q")), ["owner", "other"]).groupBy("owner", "value").agg(F.max(F.col("q") * (1 - F.pow(F.lit(epsilon), F.col("c")))).alias("via"))
    return pop.join(via, ["owner", "value"], "left").select("owner", "value", F.greatest("pop", F.coalesce("via", F.lit(0.0))).alias("weight"))


def learn_weights(records: DataFrame, gold: DataFrame, most: int = 1000, block_threshold: float | None = 0.8) -> DataFrame:
    """role, kind, agree, differ: P(same group | values agree) and P(other group | values differ), over the pairs of a block.

    Learned from the ``most`` labelled records that come first by a hash. kind 'distinct' counts values of one group alone,
    'shared' the others, 'all' both; each rate has one pair more for and against. Pairs are counted by group sizes, none is listed.
    """
    r = records.drop("gold").join(gold, "rid").where("gold is not null").withColumn("order", F.md5(F.concat(F.col("rid").cast("string"), F.lit("|w")))).orderBy("order", "rid").limit(most)
    r = materialise(r.select("rid", "name", "phone", "url", "gold"), "sample")
    values = F.array(*[F.struct(F.lit(role).alias("role"), F.lit(c).alias("attr"), F.col(c).alias("value")) for role, c in (("com", "name"), ("dom", "phone"), ("dom", "url"))])
    v = blocks(r, block_threshold).join(r, "rid").select("block", "gold", F.explode(values).alias("v")).select("block", "gold", "v.*").where("value is not null")
    v = materialise(v, "labelled")  # counted in six ways
    pairs = F.sum(F.col("n") * (F.col("n") - 1) / 2)
    sizes = lambda *by: v.groupBy("role", *by).agg(F.count("*").alias("n"))
    cell = sizes("attr", "value", "block", "gold")
    kind = cell.groupBy("role", "attr", "value").agg(F.when(F.countDistinct("gold") == 1, "distinct").otherwise("shared").alias("kind"))
    same = cell.join(kind, ["role", "attr", "value"]).groupBy("role", "kind").agg(pairs.alias("both"))
    agree = sizes("attr", "value", "block").join(kind, ["role", "attr", "value"]).groupBy("role", "kind").agg(pairs.alias("agree"))
    one = same.join(agree, ["role", "kind"])
    one = one.unionByName(one.groupBy("role").agg(F.sum("both").alias("both"), F.sum("agree").alias("agree")).withColumn("kind", F.lit("all")))
    every = sizes("attr", "block").groupBy("role").agg(pairs.alias("pairs"))
    together = sizes("attr", "block", "gold").groupBy("role").agg(pairs.alias("group"))
    total = one.where("kind = 'all'").select("role", F.col("both").alias("b"), F.col("agree").alias("a")).join(every, "role").join(together, "role")
    rate = total.select("role", ((F.col("pairs") - F.col("a") - F.col("group") + F.col("b") + 1) / (F.col("pairs") - F.col("a") + 2)).alias("differ"))
    return one.join(rate, "role").select("role", "kind", ((F.col("both") + 1) / (F.col("agree") + 2)).alias("agree"), "differ")


def weights_of(learned: DataFrame, mode: str = "double") -> Weights:
    """The learned rates as weights; single mode has one pair for all values. A kind without any value takes the rates of all."""
    found = {(x.role, x.kind): (x.agree, x.differ) for x in learned.collect()}  # six rows at most
    pair = lambda role, kind: found.get((role, kind)) or found.get((role, "all")) or getattr(Weights(), role)
    if mode == "single":
        return Weights(*(2 * (pair("com", "all"), pair("dom", "all"))), mode=mode)
    return Weights(pair("com", "shared"), pair("dom", "shared"), pair("com", "distinct"), pair("dom", "distinct"))


def _solve(settings: Settings):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        found = []
        for eid, g in pdf.groupby("eid", sort=True):
            values: Counter = Counter()
            for row in g.itertuples():
                if row.name is not None:
                    values[("com", "name", row.alike)] += 1
                for attr, v in {("phone", row.phone), ("url", row.url), ("url", row.url2)}:
                    if isinstance(v, str) and v:
                        values[("dom", attr, v)] += 1
                for attr in ("state", "category"):
                    v = getattr(row, attr)
                    if isinstance(v, str) and v:
                        values[("multi", attr, v)] += 1
            found.append(Element(eid, bool(g["is_core"].iloc[0]), len(g), values))
        outside = frozenset(("com", "name", n) for n in pdf.loc[pdf["elsewhere"] & pdf["name"].notna(), "alike"])
        got = cluster_block(found, settings, outside)
        return pd.DataFrame(list(got.items()), columns=["eid", "group_id"])

    return run


@dataclass(frozen=True)
class Packed:
    """Elements with their block and evidence component, and each record's close-name block; shared by all settings."""

    elements: DataFrame
    rows: DataFrame
    alike: DataFrame


def pack(records: DataFrame, cores: DataFrame, block_threshold: float | None = CLOSE, pairs: DataFrame | None = None) -> Packed:
    """Evidence components: elements of a block that share a dominant value. Inside a block, others only meet through their
    names, so a block of one very common name is not one task. Names of one class (``alike``) agree."""
    e = materialise(elements(records, cores), "elements")
    if pairs is None and block_threshold is not None:
        pairs = close_names(records, min(block_threshold, ALIKE))
    alike = materialise(blocks(records, ALIKE, pairs).withColumnRenamed("block", "alike"), "alike")
    base = records.select("rid", "name", "phone", "url", "url2", "state", "category").join(e, "rid").join(alike, "rid").join(blocks(records, block_threshold, pairs), "rid")
    base = materialise(base, "blocked")
    value = F.explode(F.array_compact(F.array("phone", "url", "url2")))
    links = base.select("eid", "block", value.alias("v")).select("eid", F.concat_ws("|", "block", "v").alias("clique")).distinct()
    comp = record_components(links.select(F.col("eid").alias("rid"), "clique")).select(F.col("rid").alias("eid"), F.col("comp").alias("task"))
    rows = base.join(materialise(comp, "tasks"), "eid", "left").withColumn("task", F.coalesce("task", "eid"))
    tasks = rows.groupBy("block", "alike").agg((F.min("task") < F.max("task")).alias("elsewhere"))
    alone = rows.groupBy("block", "task").agg((F.min("eid") == F.max("eid")).alias("alone"))
    return Packed(e, materialise(rows.join(tasks, ["block", "alike"]).join(alone, ["block", "task"]), "packed"), alike.withColumnRenamed("alike", "block"))


def assign(packed: Packed, settings: Settings = Settings()) -> DataFrame:
    """rid, group_id (smallest element of the group): clusters of each evidence component, then distinct names."""
    got = dealt(packed.rows.where(~F.col("alone")), "block", "task").groupBy("block", "task").applyInPandas(_solve(settings), "eid long, group_id long")
    got = got.unionByName(packed.rows.where("alone").select("eid", F.col("eid").alias("group_id")).distinct())
    groups = packed.elements.join(got, "eid").select("rid", "is_core", "group_id")
    if settings.weights.mode == "single" or cluster_is_below(settings):
        return groups.select("rid", "group_id")
    return _distinct_names(packed.alike, materialise(groups, "clusters"))


def cluster_elements(records: DataFrame, cores: DataFrame, settings: Settings = Settings(), block_threshold: float | None = 0.8) -> DataFrame:
    """rid, group_id for elements given by ``cores(rid, core)`` and the other records."""
    return assign(pack(records, cores, block_threshold), settings)


def cluster_is_below(settings: Settings) -> bool:
    """Whether agreement on a distinct common value alone stays below the threshold."""
    agree, differ = settings.weights.com_distinct[0], settings.weights.effective("dom", 0.0)
    return agree <= settings.theta * (agree + differ)


def _distinct_names(alike: DataFrame, groups: DataFrame) -> DataFrame:
    """A name that only one group with cores bears is distinct, and weighs more: satellites left alone under it join that group."""
    named = groups.join(alike, "rid")
    bearing = named.where("is_core").groupBy("block").agg(F.min("group_id").alias("g"), F.max("group_id").alias("g2")).where("g = g2").select("block", "g")
    alone = named.groupBy("group_id").agg(F.count("*").alias("n"))
    out = named.join(alone, "group_id").join(bearing, "block", "left")
    return out.select("rid", F.when((F.col("n") == 1) & ~F.col("is_core"), F.coalesce("g", "group_id")).otherwise(F.col("group_id")).alias("group_id"))


def two_stage(records: DataFrame, k: int = ROBUST, settings: Settings = Settings(), stages: str = "both", strategy: str = "full", threshold: float | None = NAME, pairs: DataFrame | None = None) -> DataFrame:
    """rid, group_id. stages: 'both', 'core_only' (others are singletons), 'cluster_only' (every record an element without core).

    Records are linked if their names are more similar than ``threshold`` (None: equal) and they share a dominant value.
    ``pairs`` are their close names, down to ``CLOSE`` and the threshold, if they are known."""
    if pairs is None:
        pairs = close_names(records, CLOSE if threshold is None else min(CLOSE, threshold))
    if stages == "cluster_only":
        # every record is a core of its own
        return assign(pack(records, records.select("rid", F.col("rid").alias("core")), CLOSE, pairs), settings)
    cores = materialise(find_cores(graph(records, threshold, pairs), k, strategy), "cores")
    if stages == "core_only":
        return elements(records, cores).select("rid", F.col("eid").alias("group_id"))
    return assign(pack(records, cores, CLOSE, pairs), settings)


def sv_index(sims: DataFrame, alpha: float = 0.01, beta: float = 0.02) -> DataFrame:
    """``sims(eid, cluster, own, sim)`` -> eid, a, b, s: silhouette of each element from its similarities."""
    by = W.Window.partitionBy("eid")
    s = sims.select("eid", F.max(F.when(F.col("own"), F.col("sim"))).over(by).alias("a"), F.max(F.when(~F.col("own"), F.col("sim"))).over(by).alias("b")).distinct()
    s = s.select("eid", "a", F.coalesce("b", F.lit(0.0)).alias("b"))
    return s.withColumn("s", (F.col("a") - F.col("b") + alpha) / (F.greatest("a", "b") + beta))
