"""Benchmark decontamination in DataFrame operations only.

The windows of all benchmark items (ten consecutive words; a shorter item is one window) form a
broadcast hash set, if their counted size allows; else the same join shuffles. Every document's
windows are hashed and looked up; hits are verified word by word on the documents that had any, by their spelling.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import materialise
from .common import LOWER, UPPER

WINDOW = 10
#: Windows of the benchmark up to which the set is broadcast (24 bytes each); documents with hits up to which their keys are.
BROADCAST_WINDOWS, BROADCAST_HITS = 4_000_000, 1_000_000
_OTHER = "".join(chr(c) for c in [*range(0x00, 0x30), *range(0x3A, 0x41), *range(0x5B, 0x61), *range(0x7B, 0x80)])


def words(text: Column) -> Column:
    """Words ``[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+`` after A-Z are lower-cased; none for null."""
    # \x01 would do as well as the space: every ASCII character that isn't part of a word becomes one blank
    blank = F.translate(text, UPPER + _OTHER, LOWER + " " * len(_OTHER))
    return F.coalesce(F.array_remove(F.split(blank, " "), ""), F.array().cast("array<string>"))


def _windows(w: Column, lengths: list[int]) -> Column:
    """Hashes of all windows of these numbers of words: in order, one length after the other."""
    none = F.array().cast("array<bigint>")
    one = lambda n: F.transform(F.sequence(F.lit(1), F.size(w) - (n - 1)), lambda i: F.xxhash64(F.slice(w, i, F.lit(n)), F.lit(n)))
    return F.concat(none, *[F.when(F.size(w) >= n, one(n)).otherwise(none) for n in lengths])


def _place(at: Column, n: Column, length: Column, lengths: list[int]) -> Column:
    """First word of the window that :func:`_windows` lists at a place, of a text of n words."""
    before = sum((F.when(length > m, F.greatest(n - (m - 1), F.lit(0))).otherwise(0) for m in lengths), F.lit(0))
    return at - before


def benchmark_windows(benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """``benchmark(item_id, text)`` -> h, len, win (the words, space-joined), items: one row per distinct window."""
    b = benchmark.select("item_id", words(F.col("text")).alias("w")).where(F.size("w") > 0)
    length = F.least(F.size("w"), F.lit(window))
    b = b.select("item_id", length.alias("len"), F.explode(F.transform(F.sequence(F.lit(1), F.size("w") - length + 1), lambda i: F.slice("w", i, length))).alias("g"))
    return b.groupBy("len", "g").agg(F.array_sort(F.collect_set(F.col("item_id").cast("string"))).alias("items")).select(F.xxhash64("g", "len").alias("h"), "len", F.array_join("g", " ").alias("win"), "items")


def key() -> Column:
    """Equal rows (doc_id and text) share a key, and their hits."""
    return F.unhex(F.md5(F.concat_ws("|", F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), "text")))


def find_hits(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """``docs(doc_id, text)`` -> key, n_hit (words), items (sorted), for the documents with verified hits; one row per :func:`key`.

    All documents are read once for their hashed windows, and only those that have any of the set once more for their words.
    The texts themselves are shuffled only if documents with hits are too many for a broadcast of their keys.
    """
    grams = materialise(benchmark_windows(benchmark, window), "grams")
    counts = {r["len"]: r["n"] for r in grams.groupBy("len").agg(F.count("*").alias("n")).collect()}  # at most `window` rows
    side, lengths = grams.groupBy("h").agg(F.collect_list(F.struct("len", "win", "items")).alias("all")), sorted(counts)
    if sum(counts.values()) <= BROADCAST_WINDOWS:
        side = F.broadcast(side)
    probe = docs.where("text is not null").select(key().alias("key"), words(F.col("text")).alias("w"))
    probe = probe.select("key", F.size("w").alias("n"), F.posexplode(_windows(F.col("w"), lengths)).alias("at", "h"))
    met = probe.join(side, "h").select("key", "n", "at", F.explode("all").alias("g"))
    found = met.select("key", F.struct(_place(F.col("at"), F.col("n"), F.col("g.len"), lengths).alias("pos"), "g").alias("hit"))
    found = materialise(found.groupBy("key").agg(F.collect_set("hit").alias("raw")), "hits")
    few = found.count() <= BROADCAST_HITS
    texts = docs.where("text is not null").select(key().alias("key"), "text").join(_maybe(found.select("key"), few), "key", "left_semi").select("key", words(F.col("text")).alias("w")).dropDuplicates(["key"])
    spelled = lambda h: F.array_join(F.slice("w", F.greatest(h["pos"], F.lit(0)) + 1, h["g"]["len"]), " ")
    hits = texts.join(found, "key").select("key", F.filter("raw", lambda h: h["g"]["win"] == spelled(h)).alias("hits")).where(F.size("hits") > 0)
    spans = F.flatten(F.transform("hits", lambda h: F.sequence(h["pos"], h["pos"] + h["g"]["len"] - 1)))
    return hits.select("key", F.size(F.array_distinct(spans)).cast("long").alias("n_hit"), F.array_sort(F.array_distinct(F.flatten(F.col("hits.g.items")))).alias("items"))


def _maybe(df: DataFrame, small: bool) -> DataFrame:
    return F.broadcast(df) if small else df


def report(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated; one row per row of ``docs``. Null texts have no words."""
    d = docs.select("doc_id", "text")
    hits = materialise(find_hits(d, benchmark, window), "contaminated")
    d = d.select("doc_id", F.size(words(F.col("text"))).cast("long").alias("n_words"), key().alias("key")).join(_maybe(hits, hits.count() <= BROADCAST_HITS), "key", "left")
    items, n_hit = F.coalesce("items", F.array().cast("array<string>")), F.coalesce("n_hit", F.lit(0))
    return d.select("doc_id", "n_words", n_hit.cast("long").alias("n_hit"), F.size(items).cast("long").alias("n_items"), F.sha2(F.array_join(items, ","), 256).alias("items_sha256"), (n_hit > 0).alias("contaminated"))


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, min_words: int = WINDOW) -> DataFrame:
    """``docs`` without the rows of which at least ``min_words`` (one or more) words lie in benchmark windows; columns as they were."""
    hits = materialise(find_hits(docs.select("doc_id", "text"), benchmark, window).where(F.col("n_hit") >= max(1, min_words)).select(F.col("key").alias("_key_of_hit")), "contaminated")
    return docs.join(_maybe(hits, hits.count() <= BROADCAST_HITS), key() == F.col("_key_of_hit"), "left_anti").select(*docs.columns)
