"""SimHash near-dedup: fingerprints, candidates by a popcount embedding, exact verification, components.

A 64-bit fingerprint is mapped to the bit counts of its 32 two-bit segments. The Manhattan distance of two such
vectors never exceeds the Hamming distance, so links within 3 bits lie within distance 3; then one half of
the segments lies within distance 1. The grid join therefore meets a fingerprint's cell of each half with
the cell itself and its neighbours at one step, and compares the fingerprints bit by bit.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.components import components
from ..session import materialise
from .common import utf8

SEED, BITS = 42, 3
#: Fingerprints of a cell beyond which it is dealt to several tasks.
HEAVY = 20_000
BLOCK = 1 << 21
_PAIRS = np.uint64(0x5555555555555555)


def shingle_hashes(text: bytes, k: int, seed: int = SEED) -> Iterator[np.ndarray]:
    """XXH64 of all k-word shingles of a text, repeats included, in blocks."""
    norm = b" ".join(text.lower().split())
    if not norm:
        return
    blanks = np.flatnonzero(np.frombuffer(norm, np.uint8) == 32)
    starts, ends = np.concatenate([[0], blanks + 1]), np.append(blanks, len(norm))
    starts, ends = (starts[:1], ends[-1:]) if len(starts) < k else (starts[: len(starts) - k + 1], ends[k - 1 :])
    h = xxhash.xxh64_intdigest
    for i in range(0, len(starts), 1 << 16):
        s, e = starts[i : i + (1 << 16)].tolist(), ends[i : i + (1 << 16)].tolist()
        yield np.fromiter((h(norm[x:y], seed) for x, y in zip(s, e, strict=True)), np.uint64, len(s))


def fingerprint(text: bytes, k: int) -> int:
    """Bits set in over half of the shingles' hashes; 0 for a text without words."""
    n, ones = 0, np.zeros(64, np.int64)
    for h in shingle_hashes(text, k):
        n += len(h)
        ones += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(ones * 2 > n, bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, k: int = 3) -> DataFrame:
    """``docs(doc_id, text)`` -> doc_id, fp (the 64 bits as a signed long). Null text has no words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = np.fromiter((fingerprint(t, k) for t in utf8(b.column(1))), np.uint64, b.num_rows)
            yield pa.record_batch([b.column(0), pa.array(fp.view(np.int64))], names=["doc_id", "fp"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, fp long")


def cells(fp: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For uint64 fingerprints: (key, side, index). Side 0 is the own cell of each half, side 1 also its neighbours."""
    counts = fp - ((fp >> np.uint64(1)) & _PAIRS)
    n, keys, sides, index = len(fp), [], [], []
    for half in range(2):
        v = ((counts >> np.uint64(32 * half)) & np.uint64(0xFFFFFFFF)).astype(np.int64)
        tag = np.int64(half) << 33
        every = np.arange(n)
        keys += [v + tag, v + tag]
        sides += [np.zeros(n, np.int8), np.ones(n, np.int8)]
        index += [every, every]
        for s in range(16):
            c = (v >> (2 * s)) & 3
            for step in (1, -1):
                ok = (c + step >= 0) & (c + step <= 2)
                keys.append(v[ok] + tag + (step << (2 * s)))
                sides.append(np.ones(int(ok.sum()), np.int8))
                index.append(every[ok])
    return np.concatenate(keys), np.concatenate(sides), np.concatenate(index)


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Links (node, smallest of its component) that hold together what the given links do."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y, label = at[: len(a)], at[len(a) :], np.arange(len(nodes))
    while True:
        low = label.copy()
        np.minimum.at(low, x, label[y])
        np.minimum.at(low, y, label[x])
        low = low[low]
        if (low == label).all():
            break
        label = low
    own = label != np.arange(len(nodes))
    return nodes[own], nodes[label[own]]


def _match(lk: np.ndarray, lf: np.ndarray, rk: np.ndarray, rf: np.ndarray, bits: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    lo, n = np.searchsorted(lk, rk, "left"), np.searchsorted(lk, rk, "right")
    n -= lo
    held = n > 0
    lo, n, rf = lo[held], n[held], rf[held]
    upto = np.cumsum(n)
    i = 0
    while i < len(n):
        j = max(i + 1, int(np.searchsorted(upto, (upto[i - 1] if i else 0) + BLOCK, "right")))
        for c in range(0, int(n[i:j].max()), BLOCK):  # one row may meet more than a block
            m = np.clip(n[i:j] - c, 0, BLOCK)
            left = np.repeat(lo[i:j] + c - (np.cumsum(m) - m), m) + np.arange(m.sum())
            x, y = lf[left], np.repeat(rf[i:j], m)
            near = (np.bitwise_count((x ^ y).view(np.uint64)) <= bits) & (x != y)
            if near.any():
                yield forest(x[near], y[near])
        i = j


def links(fps: DataFrame, bits: int = BITS) -> DataFrame:
    """Distinct ``fps(fp)`` -> a, b: links that connect exactly what all pairs within ``bits`` (at most 3) connect."""
    if not 0 <= bits <= 3:
        raise ValueError("the grid reaches 3 bits")

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(0, b.num_rows, 5000):
                fp = b.column(0).slice(i, 5000).to_numpy(zero_copy_only=False)
                key, side, at = cells(fp.view(np.uint64))
                yield pa.record_batch([pa.array(key), pa.array(side), pa.array(fp[at])], names=["key", "side", "fp"])

    def own(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            key, side, _ = cells(b.column(0).to_numpy(zero_copy_only=False).view(np.uint64))
            yield pa.record_batch([pa.array(key[side == 0])], names=["key"])

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept_key, kept = np.zeros(0, np.int64), np.zeros(0, np.int64)  # own-cell fingerprints of the last cell
        for b in batches:
            key, side, fp = (b.column(i).to_numpy(zero_copy_only=False) for i in range(3))
            left = side == 0
            lk, lf = np.concatenate([kept_key, key[left]]), np.concatenate([kept, fp[left]])
            for x, y in _match(lk, lf, key[~left], fp[~left], bits):
                yield pa.record_batch([pa.array(x), pa.array(y)], names=["a", "b"])
            last = lk == key[-1] if len(key) else np.zeros(len(lk), bool)
            kept_key, kept = lk[last], lf[last]

    rows = fps.select("fp").mapInArrow(deal, "key long, side byte, fp long").withColumn("salt", F.lit(0))
    heavy = materialise(fps.select("fp").mapInArrow(own, "key long").groupBy("key").count().where(F.col("count") > HEAVY).select("key", F.ceil(F.col("count") / HEAVY).cast("int").alias("parts")), "heavy")
    if not heavy.isEmpty():
        all_parts = F.sequence(F.lit(0), F.coalesce("parts", F.lit(1)) - 1)
        one = F.array(F.pmod(F.xxhash64("fp"), F.coalesce("parts", F.lit(1))).cast("int"))
        rows = rows.drop("salt").join(heavy, "key", "left").select("key", "side", "fp", F.explode(F.when(F.col("side") == 0, one).otherwise(all_parts)).alias("salt"))
    ordered = rows.repartition("key", "salt").sortWithinPartitions("key", "salt", "side")
    return ordered.select("key", "side", "fp").mapInArrow(meet, "a long, b long")


def near_components(docs: DataFrame, k: int = 3, bits: int = BITS) -> DataFrame:
    """``docs(doc_id, text)`` -> doc_id, fp, component_id (smallest doc_id reachable by links within ``bits``).

    Equal fingerprints are one node, so copies never meet in pairs. Rows without words share fingerprint 0.
    Null ids keep their row; they are never the smallest unless a component has no other.
    """
    f = materialise(fingerprints(docs, k), "fingerprints")
    nodes = f.groupBy("fp").agg(F.min("doc_id").alias("low"))
    comps = materialise(components(links(nodes, bits), local=0), "components")
    all_nodes = nodes.join(comps.withColumnRenamed("node", "fp"), "fp", "left").withColumn("comp", F.coalesce("comp", "fp"))
    low = all_nodes.groupBy("comp").agg(F.min("low").alias("component_id"))
    per_fp = all_nodes.select("fp", "comp").join(low, "comp").select("fp", "component_id")
    return f.join(per_fp, "fp").select("doc_id", "fp", "component_id")


def hex16(fp: Column) -> Column:
    """A signed long as 16 lower-case hex digits."""
    return F.lower(F.lpad(F.hex(fp), 16, "0"))
