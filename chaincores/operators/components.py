"""Connected components of a graph given as an edge table, by alternating star contractions."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..session import materialise, release

MAX_ROUNDS = 60
#: Distinct edges up to which one task joins them; the rounds, of several jobs each, are for more.
LOCAL = 50_000


def _large_star(e: DataFrame) -> DataFrame:
    """Link every larger neighbour of a node to the node's smallest neighbour (itself included)."""
    both = e.select("u", "v").unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
    low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    return both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))


def _small_star(e: DataFrame) -> DataFrame:
    """Link every smaller neighbour of a node, and the node, to the smallest of them."""
    low = e.groupBy("u").agg(F.min("v").alias("m"))
    return e.join(low, "u").select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v"))


def _join(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """node, comp of few edges."""
    root: dict = {}

    def find(x):
        while root.setdefault(x, x) != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    kind = None
    for batch in batches:
        kind = batch.schema.field(0).type
        for x, y in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            x, y = find(x), find(y)
            if x != y:
                root[max(x, y)] = min(x, y)
    if root:
        yield pa.record_batch([pa.array(list(root), kind), pa.array([find(x) for x in root], kind)], names=["node", "comp"])


def components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = MAX_ROUNDS, local: int = LOCAL) -> DataFrame:
    """``edges(a, b)`` -> node, comp with comp the smallest node reachable.

    Only nodes with an edge appear; self links give a component of one; rows with a null end are left out;
    repeated edges count once. The edges stay distributed: minima are pre-aggregated, the joins on a node with
    very many edges can be split at run time, and each round is written to shared storage. Raises if the
    rounds don't suffice (they are logarithmic in the length of the longest chain). Up to ``local`` edges are joined
    in one task, with the same result.
    """
    pairs = edges.select(F.col(a).alias("u"), F.col(b).alias("v")).where("u is not null and v is not null")
    # self links are written with the others, as what finds the edges would run once more for them
    written = materialise(pairs.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
    loops = written.where("u = v").select(F.col("u").alias("node"))
    e = written.where("u <> v")
    if e.count() <= local:
        kind = e.schema["u"].dataType
        found = e.coalesce(1).mapInArrow(_join, T.StructType([T.StructField("node", kind), T.StructField("comp", kind)]))
        alone = loops.distinct().join(e.select(F.col("u").alias("node")).unionByName(e.select(F.col("v").alias("node"))), "node", "left_anti")
        return found.unionByName(alone.select("node", F.col("node").alias("comp")))
    last = None
    for _ in range(max_rounds):
        n = materialise(_small_star(_large_star(e)).where("u <> v").distinct(), "edges")
        release(e)  # not the first table, which holds the self links
        e = n
        sign = tuple(e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first())
        if sign == last:
            break
        last = sign
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    roots = e.select(F.col("v").alias("node")).unionByName(loops.join(e.select(F.col("u").alias("node")), "node", "left_anti")).distinct()
    return e.select(F.col("u").alias("node"), F.col("v").alias("comp")).unionByName(roots.select("node", F.col("node").alias("comp")))
