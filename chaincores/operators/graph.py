"""The similarity graph as record-clique incidence: linear in the data, never an edge list."""

from __future__ import annotations

import math
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import pairs_above
from ..session import TASKS, materialise
from .components import components

DOMINANT = ("phone", "url", "url2")


def value_rows(records: DataFrame, dominant=DOMINANT) -> DataFrame:
    """``records(rid, name, ...)`` -> rid, name, attr, value: one row per distinct dominant value; null and blank values are missing."""
    pairs = F.array(*[F.struct(F.lit("url" if a == "url2" else a).alias("attr"), F.col(a).alias("value")) for a in dominant])
    v = records.where("rid is not null and name is not null").select("rid", "name", F.explode(pairs).alias("p")).select("rid", "name", "p.attr", "p.value")
    return v.where("value is not null and trim(value) <> ''").distinct()


#: Distinct edges of names or records up to which one task joins them, in less time than the rounds take.
LOCAL = 400_000
#: Names of a block, which meets every other block in one task's row: at most, and at least where smaller ones only serve to have work for all cores.
BLOCK, LEAST = 16_384, 1024


def block_count(names: int, cores: int) -> int:
    """Blocks to deal names to: few, as each is prepared once for every other one, but with pairs of blocks for all cores."""
    return max(1, -(-names // BLOCK), min(-(-names // LEAST), math.isqrt(2 * TASKS * cores)))


def similar_pairs(names: DataFrame, threshold: float) -> DataFrame:
    """``names(name)`` -> a < b, sim: all distinct names whose similarity is above the threshold.

    Names are dealt to blocks and each pair of blocks is one row of work, so tasks are even whatever the names. Inside it
    bounds by common characters and common prefix leave few pairs to compare, and none out; they cost some nanoseconds a pair.
    """
    distinct = names.where("name is not null").select("name").distinct()
    dealt = materialise(distinct, "distinct")
    n = block_count(dealt.count(), dealt.sparkSession.sparkContext.defaultParallelism)
    held = dealt.groupBy(F.pmod(F.xxhash64("name"), F.lit(n)).cast("int").alias("i")).agg(F.collect_list("name").alias("x"))
    after, upto = F.sequence(F.col("i"), F.lit(n - 1)), F.sequence(F.lit(0), F.col("i"))
    left = held.select("i", F.explode(after).alias("j"), "x")
    right = held.select(F.explode(upto).alias("i"), F.col("i").alias("j"), F.col("x").alias("y"))
    work = n * (n + 1) // 2

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in range(batch.num_rows):
                i, j, x, y = (batch.column(c)[r].as_py() for c in range(4))
                for a, b, sim in pairs_above(x, None if i == j else y, threshold):
                    yield pa.record_batch([pa.array(a, pa.string()), pa.array(b, pa.string()), pa.array(sim)], names=["a", "b", "sim"])

    met = left.join(right, ["i", "j"]).repartition(min(work, 2000), "i", "j")
    return met.mapInArrow(run, "a string, b string, sim double")


def name_classes(names: DataFrame, threshold: float | None = None, pairs: DataFrame | None = None) -> DataFrame:
    """``names(name)`` -> name, class: exact (class = name), or the transitive closure of similarity above the threshold.

    ``pairs(a, b, sim)`` are the similar pairs of these names, down to the threshold at least, if they are known."""
    distinct = names.where("name is not null").select("name").distinct()
    if threshold is None:
        return distinct.select("name", F.col("name").alias("class"))
    found = components(similar_pairs(names, threshold) if pairs is None else pairs.where(F.col("sim") > threshold), local=LOCAL)
    return distinct.join(found, distinct.name == found.node, "left").select("name", F.coalesce("comp", "name").alias("class"))


def v_cliques(values: DataFrame, classes: DataFrame | None = None) -> DataFrame:
    """``values(rid, name, attr, value)`` -> rid, clique: records of one name class and one value, where two or more share them.

    A clique's id is the text class/attribute/value, so that it does not depend on the layout.
    """
    v = values.withColumn("class", F.col("name")) if classes is None else values.join(classes, "name")
    v = v.select("rid", F.concat_ws("|", "class", "attr", "value").alias("clique")).distinct()
    shared = v.groupBy("clique").count().where("count > 1").select("clique")
    return v.join(shared, "clique").select("rid", "clique")


def two_dominant_cliques(values: DataFrame) -> DataFrame:
    """Edge rule of two shared dominant values: cliques by name and unordered pair of values."""
    x = values.select("rid", "name", F.concat_ws("|", "attr", "value").alias("v1"))
    y = values.select("rid", F.concat_ws("|", "attr", "value").alias("v2"))
    v = x.join(y, "rid").where("v1 < v2").select("rid", F.concat_ws("|", "name", "v1", "v2").alias("clique"))
    shared = v.groupBy("clique").count().where("count > 1").select("clique")
    return v.join(shared, "clique").select("rid", "clique")


def overlaps(incidence: DataFrame) -> DataFrame:
    """c1, c2, n (records in both), for cliques that share any; pairs come from records with several cliques only."""
    many = incidence.groupBy("rid").agg(F.sort_array(F.collect_set("clique")).alias("cs")).where(F.size("cs") > 1)
    pairs = many.select(F.explode(F.flatten(F.transform("cs", lambda a, i: F.transform(F.filter("cs", lambda b: b > a), lambda b: F.struct(a.alias("c1"), b.alias("c2")))))).alias("p"))
    return pairs.groupBy("p.c1", "p.c2").agg(F.count("*").alias("n"))


def prune_subcliques(incidence: DataFrame) -> DataFrame:
    """Without cliques contained in another; of equal ones the smallest id stays. Containment is overlap equal to size."""
    size = incidence.groupBy("clique").agg(F.count("*").alias("size"))
    o = overlaps(incidence).join(size.withColumnsRenamed({"clique": "c1", "size": "s1"}), "c1").join(size.withColumnsRenamed({"clique": "c2", "size": "s2"}), "c2")
    held = F.when(F.expr("n = s1 and s1 < s2"), F.col("c1")).when(F.expr("n = s2 and s2 <= s1"), F.col("c2"))
    gone = o.select(held.alias("clique")).where("clique is not null").distinct()
    return incidence.join(gone, "clique", "left_anti").select("rid", "clique")


def inverted_index(incidence: DataFrame) -> DataFrame:
    """rid, cliques (sorted)."""
    return incidence.groupBy("rid").agg(F.sort_array(F.collect_set("clique")).alias("cliques"))


def simplify(incidence: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(nodes(node, weight, cliques), members(rid, node)): records in exactly one clique are one weighted representative."""
    index = inverted_index(incidence)
    one = F.size("cliques") == 1
    low = index.where(one).groupBy(F.col("cliques")[0].alias("c")).agg(F.min("rid").alias("node"))
    members = index.withColumn("c", F.when(one, F.col("cliques")[0])).join(low, "c", "left").select("rid", F.coalesce("node", "rid").alias("node"), "cliques")
    nodes = members.groupBy("node").agg(F.count("*").alias("weight"), F.min("cliques").alias("cliques"))
    return nodes, members.select("rid", "node")


def graph_stats(incidence: DataFrame) -> DataFrame:
    """One row of sizes; edges are the bound over cliques of pairs, as pairs of several cliques count in each."""
    nodes, _ = simplify(incidence)
    c = incidence.groupBy("clique").agg(F.count("*").alias("s")).agg(F.count("*").alias("cliques"), F.sum("s").alias("incidences"), F.sum(F.expr("s * (s - 1) div 2")).alias("edge_bound"), F.max("s").alias("largest_clique"))
    i = inverted_index(incidence).agg(F.count("*").alias("records"), F.max(F.size("cliques")).cast("long").alias("most_cliques"))
    n = nodes.agg(F.count("*").alias("nodes"), F.max("weight").alias("largest_node"))
    return c.crossJoin(i).crossJoin(n)  # one row each


def exact_stats(incidence: DataFrame) -> DataFrame:
    """One row: edges without repetition, index rows before and after simplification, their ratio, and characters of both."""
    cliques = incidence.select(F.col("rid").alias("r2"), "clique")
    edges = incidence.join(cliques, "clique").where("rid < r2").select("rid", "r2").distinct().agg(F.count("*").alias("edges"))
    before, after = inverted_index(incidence), simplify(incidence)[0]
    size = lambda d, x: d.agg(F.count("*").alias(f"{x}_entries"), F.sum(F.size("cliques")).alias(f"{x}_rows"), F.sum(F.length(F.concat_ws(";", "cliques"))).alias(f"{x}_chars"))
    one = edges.crossJoin(size(before, "index")).crossJoin(size(after, "simplified"))  # one row each
    return one.withColumn("smaller_by", F.round(1 - F.col("simplified_entries") / F.col("index_entries"), 6))


def record_components(incidence: DataFrame) -> DataFrame:
    """rid, comp: components of records (comp is the smallest rid), through stars of each clique."""
    low = incidence.groupBy("clique").agg(F.min("rid").alias("a"))
    found = components(incidence.join(low, "clique").select("a", F.col("rid").alias("b")), local=LOCAL)
    return found.select(F.col("node").alias("rid"), "comp")


def graph(records: DataFrame, threshold: float | None = None, pairs: DataFrame | None = None) -> DataFrame:
    """Pruned incidence of the one-dominant rule: the method's first step."""
    v = value_rows(records)
    whole = v_cliques(v, None if threshold is None else name_classes(records, threshold, pairs))
    return materialise(prune_subcliques(materialise(whole, "cliques")), "incidence")
