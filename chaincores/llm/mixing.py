"""Mixing sources to target weights by systematic sampling.

Every document of a source has the same expected number of copies, target over size of the source.
Documents stand in order of size; the expected copies are prefix-summed, one random offset per
source is added, and a document is emitted once for each integer that its interval crosses. The
order by size makes the taken words follow the target closely.

The prefix sum is never taken over one group: counts by (source, size, chunk) give each chunk its
start, and rows are numbered inside a chunk only.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from .common import n_words

WEIGHTS, SHARE, MOST, CHUNKS, SEED = (3, 1, 2), 1.5, 2, 256, "mix-1"


def source_targets(sizes: DataFrame, weights=WEIGHTS, share: float = SHARE, most: int = MOST) -> DataFrame:
    """``sizes(source, source_size)`` -> source, source_size, target.

    The share of all words is dealt by weight; a source stops at ``most`` times its own words and the
    excess is dealt again among the rest: with sources in order of cap over weight, the level is the
    first at which the next source is not full.
    """
    order = W.Window.orderBy(F.col("source").isNull(), "source")
    n = len(weights)
    weight = F.element_at(F.array(*[F.lit(int(w)) for w in weights]), ((F.row_number().over(order) - 1) % n + 1).cast("int"))
    s = sizes.withColumns({"weight": weight, "cap": F.col("source_size") * most})
    by = W.Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").isNull(), "source")
    every = W.Window.partitionBy()
    rest = by.rowsBetween(W.Window.currentRow, W.Window.unboundedFollowing)
    s = s.withColumns({"left": F.lit(share) * F.sum("source_size").over(every) - (F.sum("cap").over(by.rowsBetween(W.Window.unboundedPreceding, W.Window.currentRow)) - F.col("cap")), "w_rest": F.sum("weight").over(rest)})
    s = s.withColumn("level", F.col("left") / F.col("w_rest"))
    level = F.max(F.when(F.col("level") * F.col("weight") <= F.col("cap"), F.col("level"))).over(every)
    return s.withColumn("at", level).select("source", "source_size", F.when(F.col("at").isNull(), F.col("cap").cast("double")).otherwise(F.least(F.col("cap").cast("double"), F.col("at") * F.col("weight"))).alias("target"))


def with_copies(docs: DataFrame, weights=WEIGHTS, share: float = SHARE, most: int = MOST, seed: str = SEED) -> DataFrame:
    """All rows and columns of ``docs(doc_id, text, source, ...)`` plus _size, _source_size, _target and _copies.

    Null text has size 0, null source is a source of its own (the last), repeated rows are rows like any other.
    A source without words has target 0 and no copies. Columns that start with an underscore are taken for own use.
    """
    d = docs.withColumns({"_size": n_words(F.col("text")), "_chunk": F.pmod(F.coalesce("doc_id", F.lit(0)), F.lit(CHUNKS)).cast("int")})
    keys = d.select(F.col("source").alias("s"), F.col("_size").alias("z"), F.col("_chunk").alias("c"))
    c = keys.groupBy("s", "z", "c").agg(F.count("*").alias("n"))
    b = c.groupBy("s", "z").agg(F.sum("n").alias("zn"))
    targets = source_targets(b.groupBy("s").agg(F.sum(F.col("z") * F.col("zn")).alias("source_size")).select(F.col("s").alias("source"), "source_size"), weights, share, most)
    upto = W.Window.unboundedPreceding, -1
    b = b.withColumn("before", F.coalesce(F.sum("zn").over(W.Window.partitionBy("s").orderBy("z").rowsBetween(*upto)), F.lit(0))).select("s", "z", "before")
    c = c.withColumn("inside", F.coalesce(F.sum("n").over(W.Window.partitionBy("s", "z").orderBy("c").rowsBetween(*upto)), F.lit(0)))
    t = targets.select(F.col("source").alias("ts"), "source_size", "target")
    b = b.withColumnsRenamed({"s": "bs", "z": "bz"})
    starts = c.join(b, c.s.eqNullSafe(b.bs) & (c.z == b.bz)).join(t, F.col("s").eqNullSafe(F.col("ts")))
    offset = F.conv(F.substring(F.md5(F.concat(F.coalesce("s", F.lit("")), F.lit("|" + seed))), 1, 7), 16, 10).cast("double") / float(16**7)
    starts = starts.select("s", "z", "c", (F.col("before") + F.col("inside")).alias("_start"), F.col("source_size").alias("_source_size"), F.col("target").alias("_target"), offset.alias("_u"))
    numbered = d.withColumn("_rank", F.row_number().over(W.Window.partitionBy("source", "_size", "_chunk").orderBy("doc_id")))
    on = numbered.source.eqNullSafe(starts.s) & (numbered._size == starts.z) & (numbered._chunk == starts.c)
    each = F.when(F.col("_source_size") > 0, F.col("_target") / F.col("_source_size")).otherwise(0.0)
    at = F.col("_start") + F.col("_rank")
    copies = F.floor(at * each + F.col("_u")) - F.floor((at - 1) * each + F.col("_u"))
    return numbered.join(starts, on).withColumn("_copies", copies.cast("int")).select(*docs.columns, "_size", "_source_size", "_target", "_copies")


def mix(docs: DataFrame, **settings) -> DataFrame:
    """``docs`` with each row repeated by its copies: the mixed corpus itself."""
    m = with_copies(docs, **settings)
    return m.where("_copies > 0").withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_copies")))).select(*docs.columns)
