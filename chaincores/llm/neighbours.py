"""Approximate nearest neighbours by multiprobe p-stable hashing.

Each table hashes a unit vector by k projections on normal directions, cut into slots of one width. A query
visits its own slot and others at one step in any subset of the projections, in order of estimated success (the
squared distances to the borders that are crossed). What the tables find is merged and ranked by exact cosine.

Equal vectors are one row of the index with their smallest ids. A bucket with very many rows or queries is
dealt to several tasks by count. A query that finds too few rows is compared with all of them, in blocks.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from ..session import materialise

TABLES, HASHES, WIDTH, PROBES, SEED = 5, 4, 1.2, 42, 11
HEAVY_ROWS, HEAVY_QUERIES = 200_000, 5_000
#: More than a matrix product's rounding can change a cosine.
SLACK = 1e-9


def _projections(dim: int, table: int, k: int, width: float, seed: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng([seed, table, dim])
    return rng.normal(size=(dim, k)), rng.uniform(0, width, k)


def _code(slots: np.ndarray, table: int) -> np.ndarray:
    """One long for each row of slot numbers."""
    h = np.full(slots.shape[:-1], table + 1, np.uint64)
    for i in range(slots.shape[-1]):
        h = (h ^ slots[..., i].astype(np.int64).view(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(29)
    return h.view(np.int64)


def buckets(unit: np.ndarray, table: int, probes: int, k: int = HASHES, width: float = WIDTH, seed: int = SEED) -> np.ndarray:
    """Bucket codes of unit vectors in a table: column 0 the own bucket, then perturbed ones by estimated success."""
    a, b = _projections(unit.shape[1], table, k, width, seed)
    at = (unit @ a + b) / width
    slot = np.floor(at).astype(np.int64)
    if probes <= 1:
        return _code(slot, table)[:, None]
    rest = at - slot
    steps = np.array(list(product((0, -1, 1), repeat=k)), np.int64)
    cost = (steps == -1) @ (rest**2).T + (steps == 1) @ ((1 - rest) ** 2).T  # (steps, rows)
    order = np.argsort(cost, axis=0, kind="stable")[: min(probes, len(steps))].T
    return _code(slot[:, None, :] + steps[order], table)


def _clean(vectors: DataFrame) -> DataFrame:
    """Rows that take part: no null, non-finite or zero vectors, nor nulls inside; doubles."""
    v = F.col("embedding").cast("array<double>")
    big = F.lit(float("inf"))
    ok = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < big)) & F.exists("v", lambda x: x != 0)
    return vectors.select("vec_id", v.alias("v")).where("vec_id is not null and v is not null").where(ok)


def _matrix(column: pa.Array) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1)


def search(vectors: DataFrame, queries: DataFrame, top: int = 5, tables: int = TABLES, probes: int = PROBES, k: int = HASHES, width: float = WIDTH, seed: int = SEED) -> DataFrame:
    """``vectors(vec_id, embedding)``, ``queries`` of the same columns -> query_id, rank, vec_id, score.

    A query never finds the row of its own id; of several vectors of a query id the least one asks. Ties go to the smaller id; repeated (id, vector) rows count once.
    Vectors of another length than the query's are no candidates. Fewer than ``top`` candidates: all of them.
    """

    def hashed(count: int):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                dims = np.asarray(b.column(1).value_lengths())
                for dim in np.unique(dims):
                    part = b.filter(pa.array(dims == dim))
                    for i in range(0, part.num_rows, 1000):
                        p = part.slice(i, 1000)
                        x = _matrix(p.column(1))
                        x = _scaled(x)
                        x /= np.linalg.norm(x, axis=1, keepdims=True)
                        for t in range(tables):
                            codes = buckets(x, t, count, k, width, seed) + dim
                            keys = codes.ravel()
                            at = pa.array(np.repeat(np.arange(p.num_rows), codes.shape[1]))
                            yield pa.record_batch([pa.array(keys), p.column(0).take(at), p.column(1).take(at)], names=["key", "ids", "v"])

        return run

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, qv, qid, best = None, [], [], None
        qscale = qn = None

        def out() -> Iterator[pa.RecordBatch]:
            if best is not None and len(best[0]):
                q, r = np.nonzero(best[1] >= 0)
                yield pa.record_batch([pa.array(qid_arr[q]), pa.array(best[1][q, r]), pa.array(best[0][q, r])], names=["query_id", "vec_id", "score"])

        qid_arr = np.zeros(0, np.int64)
        for b in batches:
            group, side = (np.asarray(b.column(i)) for i in (0, 1))
            cuts = [0, *(np.flatnonzero((group[1:] != group[:-1]) | (side[1:] != side[:-1])) + 1).tolist(), len(group)]
            for i, j in zip(cuts, cuts[1:]):
                if group[i] != now:
                    yield from out()
                    now, qv, qid, best = group[i], [], [], None
                ids, v = b.column(2).slice(i, j - i), b.column(3).slice(i, j - i)
                if side[i] == 0:
                    qid.append(_matrix(ids)[:, 0])
                    qv.append(_matrix(v))
                elif qv:
                    if best is None:
                        qid_arr, qm = np.concatenate(qid), np.concatenate(qv)
                        qscale = _scaled(qm)
                        qn = np.linalg.norm(qscale, axis=1)
                        best = np.full((len(qm), top), -np.inf), np.full((len(qm), top), -1, np.int64)
                    for c in range(0, j - i, 2000):
                        best = _better(best, qscale, qn, qid_arr, ids.slice(c, 2000), v.slice(c, 2000), top)
        yield from out()

    clean = materialise(_clean(vectors), "vectors")
    index = _collapse(clean, top + 1)
    asked = materialise(_clean(queries).groupBy("vec_id").agg(F.min("v").alias("v")).select(F.array("vec_id").alias("ids"), "v"), "queries")
    schema = "key long, ids array<long>, v array<double>"
    found = _scan_buckets(asked.select("ids", "v").mapInArrow(hashed(probes), schema), index.select("ids", "v").mapInArrow(hashed(1), schema), scan)
    found = materialise(found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score")), "found")
    poor = asked.select("ids", "v", F.col("ids")[0].alias("q")).join(found.groupBy("query_id").count().where(F.col("count") >= top), F.col("q") == F.col("query_id"), "left_anti")
    poor = materialise(poor.select("ids", "v"), "poor")
    if not poor.isEmpty():
        alone = lambda d: d.select(F.size("v").cast("long").alias("key"), "ids", "v")
        rest = _scan_buckets(alone(poor), alone(index), scan)
        found = found.unionByName(rest).groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    by = W.Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(by)).where(F.col("rank") <= top).select("query_id", "rank", "vec_id", "score")


def _collapse(clean: DataFrame, n: int) -> DataFrame:
    """One row per distinct vector with its n smallest ids; partial results of a very common vector stay n long."""
    by = W.Window.partitionBy("v").orderBy("vec_id")
    few = clean.dropDuplicates(["vec_id", "v"]).withColumn("at", F.row_number().over(by)).where(F.col("at") <= n)
    return few.groupBy("v").agg(F.array_sort(F.collect_list("vec_id")).alias("ids"))


def _scaled(x: np.ndarray) -> np.ndarray:
    """Rows times a power of two each, so that squares neither overflow nor vanish; cosines keep every bit."""
    return np.ldexp(x, -np.frexp(np.abs(x).max(1, keepdims=True))[1])


def _scan_buckets(asked: DataFrame, index: DataFrame, scan) -> DataFrame:
    """Meet queries and rows by key; heavy keys are dealt out by their counts on both sides."""
    asked, index = materialise(asked, "asked"), materialise(index, "index")
    n = index.groupBy("key").agg(F.ceil(F.count("*") / HEAVY_ROWS).alias("a")).join(asked.groupBy("key").agg(F.ceil(F.count("*") / HEAVY_QUERIES).alias("b")), "key")
    salt = lambda c: F.pmod(F.xxhash64("v", "ids"), F.col(c)).cast("int")
    every = lambda c: F.explode(F.sequence(F.lit(0), F.col(c).cast("int") - 1))
    q = asked.join(n, "key").select("key", "ids", "v", salt("b").alias("y"), every("a").alias("x"))
    r = index.join(n, "key").select("key", "ids", "v", salt("a").alias("x"), every("b").alias("y"))
    rows = q.select(F.xxhash64("key", "x", "y").alias("g"), F.lit(0).alias("side"), "ids", "v").unionByName(r.select(F.xxhash64("key", "x", "y").alias("g"), F.lit(1).alias("side"), "ids", "v"))
    return rows.repartition("g").sortWithinPartitions("g", "side").mapInArrow(scan, "query_id long, vec_id long, score double")


def _better(best, qm, qn, qid, ids, v, top):
    """Merge the best so far with the rows of a block.

    The matrix product finds the few that can matter; their scores are computed pair by pair, so that a score depends on the
    two vectors alone and equal vectors tie.
    """
    x = _matrix(v)
    if x.shape[1] != qm.shape[1]:
        return best
    x = _scaled(x)
    xn = np.linalg.norm(x, axis=1)
    s = (qm @ x.T) / (qn[:, None] * xn[None, :])
    lists = ids.value_lengths().to_numpy(zero_copy_only=False)
    owner, flat = np.repeat(np.arange(len(lists)), lists), ids.flatten().to_numpy(zero_copy_only=False)
    s = s[:, owner]
    s[qid[:, None] == flat[None, :]] = -np.inf
    may = s > -np.inf
    if s.shape[1] > top:  # all that may tie with the last
        may &= s >= np.partition(s, s.shape[1] - top, axis=1)[:, s.shape[1] - top][:, None] - SLACK
    q, r = np.nonzero(may)
    exact = np.full(s.shape, -np.inf)
    for i in range(0, len(q), 100_000):
        a, b = q[i : i + 100_000], r[i : i + 100_000]
        exact[a, b] = np.clip((qm[a] * x[owner[b]]).sum(1) / (qn[a] * xn[owner[b]]), -1.0, 1.0)
    keep = may.any(0)
    s, flat = exact[:, keep], flat[keep]
    score = np.concatenate([best[0], s], 1)
    ids2 = np.concatenate([best[1], np.broadcast_to(flat, s.shape)], 1)
    order = np.lexsort((ids2, -score), axis=1)[:, :top]
    score, ids2 = np.take_along_axis(score, order, 1), np.take_along_axis(ids2, order, 1)
    return score, np.where(np.isneginf(score), -1, ids2)
