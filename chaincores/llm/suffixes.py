"""Suffix-array dedup over many documents: bytes under a repeated string of given length.

Every window of ``length`` bytes holds a minimal hash among its grams (its anchor); equal windows have equal anchors.
So only segments (runs of windows of one anchor) whose anchor occurs again can hold repeats, and segments of one anchor
go to one shard. Equal segments are one, with a count. Each shard is sorted by :mod:`induced`. Nothing is
decided by the hashes of the grams: they only say where to look, and lose no repeat.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..session import materialise, release
from . import induced
from .common import utf8

LENGTH, GRAM = 400, 64
#: Bytes of distinct segments that a shard should hold, on average.
SHARD = 2 << 20
_MUL, _MIX = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9)
PIECE = 1 << 20


def gram_hashes(b: np.ndarray, gram: int) -> np.ndarray:
    """Hash of the ``gram`` (a power of two) bytes from each place, by doubling."""
    h, k = b.astype(np.uint64) + np.uint64(1), 1
    while k < gram:
        h = h[:-k] * _MUL + h[k:]
        h ^= h >> np.uint64(29)
        h *= _MIX
        h ^= h >> np.uint64(32)
        k *= 2
    return h


def anchors(text: bytes, length: int, gram: int = GRAM) -> Iterator[tuple[int, int, int, int]]:
    """(anchor, first window, windows, times) for the runs of windows of a text that share their anchor.

    Runs have at most ``length`` windows; times is how often the anchor's gram occurs in the run.
    """
    for base in range(0, max(0, len(text) - length + 1), PIECE):
        b = np.frombuffer(text, np.uint8, min(len(text) - base, PIECE + length - 1), base)
        h = gram_hashes(b, gram)
        span = length - gram + 1
        m = len(h)
        grid = np.full(-(-m // span) * span, np.iinfo(np.uint64).max, np.uint64)
        grid[:m] = h
        grid = grid.reshape(-1, span)
        ahead, back = np.minimum.accumulate(grid, 1).ravel(), np.minimum.accumulate(grid[:, ::-1], 1)[:, ::-1].ravel()
        low = np.minimum(back[: m - span + 1], ahead[span - 1 : m])
        cut = np.flatnonzero(np.concatenate([[True], low[1:] != low[:-1]]))
        long = np.diff(np.append(cut, len(low)))
        if (long > length).any():
            cut = np.unique(np.concatenate([cut, *[np.arange(c, c + n, length) for c, n in zip(cut[long > length], long[long > length], strict=True)]]))
            long = np.diff(np.append(cut, len(low)))
        value = low[cut]
        ends = (cut + long + (span - 1)).tolist()
        times = [int(np.count_nonzero(h[s:e] == a)) for a, s, e in zip(value, cut.tolist(), ends, strict=True)]
        yield from zip(value.view(np.int64).tolist(), (cut + base).tolist(), long.tolist(), times, strict=True)


def repeated_spans(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, shard: int = SHARD) -> DataFrame:
    """``docs(doc_id, text)`` -> _key, _spans: sorted [from, to) byte spans under repeats, for the texts that have any.

    _key is :func:`row_key`. Equal rows share a key and are repeats of one another.
    """
    gram = min(gram, 1 << ((length // 4).bit_length() - 1))

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(0, b.num_rows, 500):
                rows: list[tuple] = []
                for key, text in zip(b.column(0).slice(i, 500).to_pylist(), utf8(b.column(1).slice(i, 500)), strict=True):
                    for a, s, n, times in anchors(text, length, gram):
                        d = xxhash.xxh3_128_intdigest(text[s : s + n + length - 1])
                        rows.append((a, (d >> 64) - (1 << 63), (d & (2**64 - 1)) - (1 << 63), key, s, n, times))
                if rows:
                    yield pa.record_batch([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], names=["anchor", "h1", "h2", "key", "start", "n", "times"])

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for text, segs in zip(utf8(b.column(0)), b.column(1).to_pylist(), strict=True):
                yield pa.record_batch([pa.array([s[k] for s in segs], pa.int64()) for k in ("anchor", "h1", "h2", "copies")] + [pa.array([text[s["start"] : s["start"] + s["n"] + length - 1] for s in segs], pa.binary())], names=["anchor", "h1", "h2", "copies", "seg"])

    def sort(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []

        def out() -> pa.RecordBatch:
            segs = [s for *_, s in held]
            text = np.frombuffer(b"".join(s + bytes([induced.END]) for s in segs), np.uint8)
            mark = induced.repeated(text, length)
            at, runs = 0, []
            for (_, _, copies, _), seg in zip(held, segs, strict=True):
                n = len(seg) - length + 1
                m = np.ones(n, bool) if copies > 1 else mark[at : at + n]
                edge = np.flatnonzero(np.diff(np.concatenate([[False], m, [False]]).astype(np.int8)))
                runs.append(edge.tolist())
                at += len(seg) + 1
            return pa.record_batch([pa.array([x for x, *_ in held], pa.int64()), pa.array([x for _, x, *_ in held], pa.int64()), pa.array(runs, pa.list_(pa.int32()))], names=["h1", "h2", "runs"])

        for b in batches:
            for s, *row in zip(*(b.column(i).to_pylist() for i in range(5)), strict=True):
                if s != now:
                    if held:
                        yield out()
                    now, held = s, []
                held.append(row)
        if held:
            yield out()

    keyed = docs.select(row_key().alias("key"), "text").where(F.octet_length("text") >= length)
    found = materialise(keyed.mapInArrow(find, "anchor long, h1 long, h2 long, key long, start long, n long, times long"), "anchors")
    often = found.groupBy("anchor").agg(F.sum("times").alias("often")).where("often > 1").select("anchor")
    found2 = materialise(found.join(often, "anchor"), "repeated")
    release(found)
    one = found2.groupBy("anchor", "h1", "h2").agg(F.count("*").alias("copies"), F.min(F.struct("key", "start", "n")).alias("at"))
    lists = one.groupBy("at.key").agg(F.collect_list(F.struct("anchor", "h1", "h2", "copies", "at.start", "at.n")).alias("segs"))
    distinct_bytes = one.agg(F.sum(F.col("at.n") + length)).first()[0] or 0
    shards = max(1, -(-distinct_bytes // shard))
    segs = keyed.join(lists, "key").select("text", "segs").mapInArrow(cut, "anchor long, h1 long, h2 long, copies long, seg binary")
    segs = segs.withColumn("shard", F.pmod(F.xxhash64("anchor"), F.lit(shards)))
    order = segs.repartition(int(shards), "shard").sortWithinPartitions("shard").select("shard", "h1", "h2", "copies", "seg")
    marked = order.mapInArrow(sort, "h1 long, h2 long, runs array<int>").where(F.size("runs") > 0)
    pairs = F.transform(F.sequence(F.lit(0), F.size("runs") - 2, F.lit(2)), lambda i: F.struct((F.col("start") + F.get("runs", i)).alias("a"), (F.col("start") + F.get("runs", i + 1) + (length - 1)).alias("b")))
    return found2.join(marked.dropDuplicates(["h1", "h2"]), ["h1", "h2"]).select("key", F.explode(pairs).alias("s")).groupBy(F.col("key").alias("_key")).agg(F.array_sort(F.collect_set("s")).alias("_spans"))


def row_key():
    return F.xxhash64(F.coalesce("doc_id", F.lit(-(1 << 62))), F.col("text"))


def _merge(spans: list[dict]) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for s in spans or ():
        if out and s["a"] <= out[-1][1]:
            out[-1][1] = max(out[-1][1], s["b"])
        else:
            out.append([s["a"], s["b"]])
    return [(a, b) for a, b in out]


def with_spans(docs: DataFrame, length: int = LENGTH, **settings) -> DataFrame:
    """All of ``docs`` plus _spans (null where nothing repeats)."""
    spans = materialise(repeated_spans(docs, length, **settings), "spans").withColumnRenamed("_key", "_k")
    return docs.withColumn("_key", row_key()).join(spans, F.col("_key") == F.col("_k"), "left").drop("_key", "_k")


def report(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256; one row per row. Null is empty; equal rows are repeats of one another."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for text, spans in zip(utf8(b.column(1)), b.column(2).to_pylist(), strict=True):
                merged, h, at = _merge(spans), hashlib.sha256(), 0
                for x, y in merged:
                    h.update(text[at:x])
                    at = y
                h.update(text[at:])
                rows.append((len(text), sum(y - x for x, y in merged), len(merged), h.hexdigest()))
            yield pa.record_batch([b.column(0), *[pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.int64(),) * 3 + (pa.string(),), strict=True)]], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    return with_spans(docs.select("doc_id", "text"), length).mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def cut_repeats(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """``docs`` with repeated passages cut from the texts (whole characters only); texts without any stay as they are, n_chars follows."""
    names = docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for text, spans in zip(b.column(names.index("text")).to_pylist(), b.column(len(names)).to_pylist(), strict=True):
                if spans:
                    raw, parts, at = text.encode(), [], 0
                    for x, y in _merge(spans):
                        while x < y and raw[x] & 0xC0 == 0x80:
                            x += 1
                        while y > x and y < len(raw) and raw[y] & 0xC0 == 0x80:
                            y -= 1
                        parts.append(raw[at:x])
                        at = y
                    text = b"".join([*parts, raw[at:]]).decode()
                out.append(text)
            cols = list(b.columns[: len(names)])
            cols[names.index("text")] = pa.array(out, pa.string())
            if "n_chars" in names:
                cols[names.index("n_chars")] = pa.array([None if t is None else len(t) for t in out], pa.int64())
            yield pa.record_batch(cols, names=names)

    schema = T.StructType([f if f.name != "n_chars" else T.StructField("n_chars", T.LongType()) for f in docs.schema.fields])
    return with_spans(docs, length).mapInArrow(run, schema)
