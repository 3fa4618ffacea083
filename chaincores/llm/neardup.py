"""Near duplicates of texts by SimHash on word shingles, verified exactly.

Texts whose whole 64-bit SimHashes are within three bits meet by the popcount grid. At a Jaccard similarity of 0.8 such a
SimHash differs in ten bits on average, far more than a grid can reach. So a text has several more fingerprints, each a SimHash (majority of bits) of a small sample of its shingles:
those with the least hashes under the table's permutation. Texts with an equal fingerprint are candidates; a pair
of similarity s meets in a table with probability s**3, so sixteen tables miss one pair in 90,000 at 0.8. Texts of few
shingles meet without any loss instead: two sets of that similarity share one of the least hashes of each, of which there are
as many as the smaller set may lack, and one more.

Candidates never meet in all pairs: each bucket is a star around its smallest node, verified. Buckets that this leaves in
several components are solved where they lie, see :func:`link_bucket`: only nodes outside a bucket's largest component are
looked up, by their rarest shingles, and only links that join components come out. A bucket with many shingles is dealt to
several tasks.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from ..operators.components import components
from ..session import materialise, release
from .common import utf8
from .simhash import links as grid_links
from .simhash import shingle_hashes

SHINGLE, SIMILAR, TABLES, SAMPLE = 5, 0.8, 16, 3
#: Sets of up to so many shingles meet by their least hashes; the larger of them also in the tables, as larger partners do.
SHORT = 40
#: Bits of the sketch, and how many may differ in a star: 13 do at 0.8 on average, more than 28 once in a hundred thousand
#: pairs. Those are no star's links then; they are found with what the stars leave apart.
BITS, MOST = 128, 28
#: Shingles of a bucket, and of those looked up in it, beyond which each is dealt to several tasks.
HELD, ASKED = 4_000_000, 2_000_000
_MORE = (np.random.default_rng(19).integers(1, 2**63, BITS, dtype=np.uint64) << np.uint64(1)) | np.uint64(1)
_ODD = (np.random.default_rng(17).integers(1, 2**63, 64, dtype=np.uint64) << np.uint64(1)) | np.uint64(1)


def shingle_set(text: bytes, k: int = SHINGLE) -> np.ndarray:
    """Distinct hashes of the k-word shingles."""
    parts = list(shingle_hashes(text, k))
    return np.unique(np.concatenate(parts)) if parts else np.zeros(0, np.uint64)


def sampled_fingerprints(h: np.ndarray, tables: int = TABLES, sample: int = SAMPLE) -> np.ndarray:
    """One SimHash per table over the table's sample of a shingle set; all zero for none."""
    out = np.zeros(tables, np.uint64)
    if not len(h):
        return out
    n, base = min(sample, len(h)), h ^ (h >> np.uint64(31))
    for i in range(tables):
        low = np.argpartition(base * _ODD[i], n - 1)[:n] if n < len(h) else slice(None)
        bits = np.unpackbits(h[low].view(np.uint8).reshape(n, 8), axis=1, bitorder="little")
        out[i] = np.packbits(bits.sum(0) * 2 > n, bitorder="little").view(np.uint64)[0]
    return out


def spare(n: int, similar: float) -> int:
    """So many elements of a set of n, and fewer by one may be missing from a set of that similarity: one of them is in it."""
    return n - int(np.ceil(similar * n - 1e-9)) + 1


def keys(h: np.ndarray, tables: int = TABLES, sample: int = SAMPLE, similar: float = SIMILAR, short: int = SHORT) -> np.ndarray:
    """Buckets of a shingle set; two sets of the similarity share one, surely if one of them has ``short`` shingles or fewer."""
    if not len(h):
        return np.zeros(1, np.uint64)
    out = []
    if len(h) <= short:
        n = spare(len(h), similar)
        mixed = (h ^ (h >> np.uint64(31))) * _ODD[41]
        out.append(h[np.argpartition(mixed, n - 1)[:n] if n < len(h) else slice(None)] * _ODD[42])
    if len(h) >= int(similar * short):
        out.append((sampled_fingerprints(h, tables, sample) + np.arange(tables, dtype=np.uint64)) * _ODD[40])
    return np.concatenate(out)


def sketch(h: np.ndarray, bits: int = BITS) -> np.ndarray:
    """One bit of the least hash under each of many permutations: at similarity s a bit of two sets differs with probability (1 - s) / 2."""
    low = np.full(bits, np.iinfo(np.uint64).max, np.uint64)
    for i in range(0, len(h), 4096):
        part = h[i : i + 4096]
        low = np.minimum(low, ((part[None, :] ^ (part[None, :] >> np.uint64(29))) * _MORE[:bits, None]).min(1))
    return np.packbits((low >> np.uint64(20)).astype(np.uint8) & 1, bitorder="little").view(np.int64)


def close() -> Column:
    """Whether the sketches s1, s2 and t1, t2 differ in few enough bits for the similarity."""
    return F.bit_count(F.col("s1").bitwiseXOR(F.col("t1"))) + F.bit_count(F.col("s2").bitwiseXOR(F.col("t2"))) <= MOST


def node() -> Column:
    """Equal texts are one node, named by 128 bits; null is the empty text."""
    return F.unhex(F.md5(F.coalesce("text", F.lit(""))))


def whole_fingerprint(h: np.ndarray) -> int:
    """SimHash of a whole shingle set; zero for none."""
    bits = np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    return int(np.packbits(bits.sum(0, dtype=np.int64) * 2 > len(h), bitorder="little").view(np.int64)[0]) if len(h) else 0


def buckets(docs: DataFrame, k: int = SHINGLE, similar: float = SIMILAR) -> DataFrame:
    """bucket, node, s1, s2, fp: distinct. The row of a node with a null bucket holds its whole fingerprint, the others its keys."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(0, b.num_rows, 1000):
                sets = [shingle_set(t, k) for t in utf8(b.column(1).slice(i, 1000))]
                own = [keys(h, similar=similar) for h in sets]
                n = [len(x) for x in own]
                s, nodes, m = np.array([sketch(h) for h in sets]), b.column(0).slice(i, 1000), len(sets)
                at = np.concatenate([np.arange(m).repeat(n), np.arange(m)])
                key = pa.concat_arrays([pa.array(np.concatenate(own).view(np.int64)), pa.nulls(m, pa.int64())])
                fp = pa.concat_arrays([pa.nulls(sum(n), pa.int64()), pa.array([whole_fingerprint(h) for h in sets], pa.int64())])
                yield pa.record_batch([key, nodes.take(pa.array(at)), pa.array(s[at, 0]), pa.array(s[at, 1]), fp], names=["bucket", "node", "s1", "s2", "fp"])

    return docs.select(node().alias("node"), "text").mapInArrow(run, "bucket long, node binary, s1 long, s2 long, fp long").distinct()


def grid_buckets(fps: DataFrame) -> DataFrame:
    """``fps(fp, node, s1, s2)`` -> bucket, node, s1, s2: texts whose whole fingerprints the popcount grid links, or equal ones, share a bucket."""
    comp = materialise(components(grid_links(fps.select("fp").distinct()), local=0), "grid").withColumnsRenamed({"node": "fp", "comp": "c"})
    return fps.join(comp, "fp", "left").select(F.xxhash64(F.coalesce("c", "fp"), F.lit("grid")).alias("bucket"), "node", "s1", "s2")


def _sets(docs: DataFrame, ids: DataFrame, k: int) -> DataFrame:
    """id, s: the shingle sets of the nodes ``ids(id)``, as sorted 64-bit hashes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(0, b.num_rows, 500):
                sets = [shingle_set(t, k).view(np.int64) for t in utf8(b.column(1).slice(i, 500))]
                yield pa.record_batch([b.column(0).slice(i, 500), pa.array(sets, pa.list_(pa.int64()))], names=["id", "s"])

    texts = docs.select(node().alias("id"), "text").join(ids.distinct(), "id", "left_semi")
    return texts.mapInArrow(run, "id binary, s array<long>").groupBy("id").agg(F.first("s").alias("s"))


def _verified(pairs: DataFrame, sets: DataFrame, similar: float) -> DataFrame:
    """The ``pairs(a, b)`` whose shingle sets have at least the similarity; sets without shingles are equal."""
    both = pairs.join(sets.select(F.col("id").alias("a"), F.col("s").alias("x")), "a").join(sets.select(F.col("id").alias("b"), F.col("s").alias("y")), "b")
    common = F.size(F.array_intersect("x", "y"))
    return both.where(common >= similar * (F.size("x") + F.size("y") - common) - 1e-9).select("a", "b")


def link_bucket(sets: list[np.ndarray], label: np.ndarray, side: np.ndarray, similar: float) -> list[tuple[int, int]]:
    """Links between sets of the similarity that join all components (``label``) which hold together through sets that are asked.

    side: 0 is asked, 1 is of the largest component, 2 is another one that other tasks ask. The most typical of the largest
    component go first, as long as they draw others in: of copies edited at random they are nearest to the original. Then each
    asked set that is still apart is looked up by its rarest shingles, as many as leave no similar set out.
    """
    n, label, asked = len(sets), label.copy(), side == 0
    size = np.fromiter((len(s) for s in sets), np.int64, n)
    flat, start = np.concatenate(sets), np.concatenate([[0], np.cumsum(size)])
    code = np.unique(flat, return_inverse=True)[1]
    often = np.bincount(code)
    owner = np.repeat(np.arange(n), size)[np.argsort(code, kind="stable")]
    first = np.concatenate([[0], np.cumsum(often)[:-1]]).astype(np.int64) if len(often) else np.zeros(0, np.int64)
    found: list[tuple[int, int]] = []

    def holders(codes: np.ndarray) -> np.ndarray:
        many = often[codes]
        return owner[np.repeat(first[codes] - np.cumsum(many) + many, many) + np.arange(many.sum())]

    def meet(i: int) -> int:
        """Join the set with all that are similar; how many components went."""
        mine = code[start[i] : start[i + 1]]
        common = np.bincount(holders(mine), minlength=n)
        near = np.flatnonzero((common >= similar * (size[i] + size - common) - 1e-9) & (label != label[i]))
        others, at = np.unique(label[near], return_index=True)
        found.extend((i, int(j)) for j in near[at])
        if len(others):
            label[np.isin(label, others)] = label[i]
        return len(others)

    typical = np.add.reduceat(np.append(often[code], 0), start[:-1]) * (size > 0) / np.maximum(size, 1)
    still = np.flatnonzero(side == 1)
    for i in still[np.argsort(-typical[still], kind="stable")]:
        apart = np.count_nonzero(asked & (label != label[i]))
        if not apart or meet(int(i)) * 50 < apart:
            break
    for i in np.flatnonzero(asked):
        if len(still) and label[i] == label[still[0]]:
            continue
        mine = code[start[i] : start[i + 1]]
        rare = mine[np.argsort(often[mine], kind="stable")[: spare(int(size[i]), similar)]]
        if not size[i] or (label[holders(rare)] != label[i]).any():
            meet(int(i))
    return found


def _link_open(rest: DataFrame, sets: DataFrame, similar: float) -> DataFrame:
    """``rest(bucket, node, comp)`` -> a, b: links that join all that is similar in each bucket."""

    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []

        def out() -> pa.RecordBatch | None:
            ids, comps, sides = (pa.concat_arrays([x[c] for x in held]) for c in range(3))
            label = np.asarray(comps.dictionary_encode().indices).astype(np.int64)
            sets = [np.asarray(s) for x in held for s in np.split(np.asarray(x[3].flatten()), np.cumsum(np.asarray(x[3].value_lengths()))[:-1])]
            pairs = link_bucket(sets, label, np.asarray(sides), similar)
            if pairs:
                return pa.record_batch([ids.take(pa.array([p[c] for p in pairs])) for c in range(2)], names=["a", "b"])

        for b in batches:
            group = np.stack([np.asarray(b.column(c)) for c in range(3)])
            cuts = [0, *(np.flatnonzero((group[:, 1:] != group[:, :-1]).any(0)) + 1).tolist(), b.num_rows] if b.num_rows else []
            for i, j in zip(cuts, cuts[1:]):
                if (key := tuple(group[:, i].tolist())) != now:
                    if held and (links := out()):
                        yield links
                    now, held = key, []
                held.append([b.column(c).slice(i, j - i) for c in range(3, 7)])
        if held and (links := out()):
            yield links

    sized = materialise(rest.join(sets.withColumnRenamed("id", "node"), "node").withColumn("m", F.size("s") + 1), "open")
    per = sized.groupBy("bucket", "comp").agg(F.sum("m").alias("m"))
    per = per.groupBy("bucket").agg(F.max_by("comp", F.struct("m", "comp")).alias("main"), F.sum("m").alias("all"), F.max("m").alias("most"))
    parts = per.select("bucket", "main", F.ceil(F.col("all") / HELD).cast("int").alias("held"), F.ceil((F.col("all") - F.col("most")) / ASKED).cast("int").alias("asked"))
    every = lambda c: F.sequence(F.lit(0), F.col(c) - 1)
    own = lambda c: F.array(F.pmod(F.xxhash64("node"), F.col(c)).cast("int"))
    rows = sized.join(parts, "bucket").withColumn("out", F.col("comp") != F.col("main"))
    one = (F.col("held") == 1) & (F.col("asked") == 1)
    asked = rows.where("out").withColumns({"side": F.lit(0).cast("byte"), "x": own("asked"), "y": every("held")})
    held = rows.where(~(F.col("out") & one)).withColumns({"side": F.when(F.col("out"), 2).otherwise(1).cast("byte"), "x": every("asked"), "y": own("held")})
    dealt = asked.unionByName(held).withColumn("x", F.explode("x")).withColumn("y", F.explode("y")).select("bucket", "x", "y", "node", "comp", "side", "s")
    return dealt.repartition("bucket", "x", "y").sortWithinPartitions("bucket", "x", "y").mapInArrow(solve, "a binary, b binary")


def groups(docs: DataFrame, k: int = SHINGLE, similar: float = SIMILAR) -> DataFrame:
    """``docs(doc_id, text)`` -> node, comp for the nodes linked to others (comp is the least node)."""
    dealt = materialise(buckets(docs, k, similar), "buckets")
    grid = grid_buckets(dealt.where("bucket is null"))
    b = dealt.where("bucket is not null").select("bucket", "node", "s1", "s2").unionByName(grid)
    least = b.groupBy("bucket").agg(F.min(F.struct("node", "s1", "s2")).alias("l"), F.count("*").alias("n")).where("n > 1").select("bucket", F.col("l.node").alias("a"), F.col("l.s1").alias("t1"), F.col("l.s2").alias("t2"))
    star = materialise(b.join(least, "bucket").where("node <> a").where(close()).select("a", F.col("node").alias("b")).distinct(), "star")
    ids = star.select(F.col("a").alias("id")).unionByName(star.select(F.col("b").alias("id")))
    sets = materialise(_sets(docs, ids, k), "sets")
    links = materialise(_verified(star, sets, similar), "links")
    release(star)
    release(sets)
    comp = materialise(components(links, local=0), "comp")
    rest = materialise(_apart(b.select("bucket", "node").join(comp, "node", "left").select("bucket", "node", F.coalesce("comp", "node").alias("comp"))), "open")
    release(dealt)
    if rest.isEmpty():
        return comp
    sets = materialise(_sets(docs, rest.select(F.col("node").alias("id")), k), "sets")
    more = materialise(_link_open(rest, sets, similar), "links")
    release(sets)
    release(rest)
    return comp if more.isEmpty() else components(links.unionByName(more), local=0)


def _apart(labelled: DataFrame) -> DataFrame:
    """The rows of ``labelled(bucket, node, comp)`` in buckets with more than one component."""
    return labelled.join(labelled.groupBy("bucket").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo < hi").select("bucket"), "bucket")


def keep_one(docs: DataFrame, k: int = SHINGLE, similar: float = SIMILAR) -> DataFrame:
    """One row of ``docs`` per group of near duplicates: that of the least doc_id (nulls last); columns as they were.

    Equal rows are copies: one stays. Texts without words (null or empty too) are copies of each other.
    """
    comp = materialise(groups(docs, k, similar), "groups").select(F.col("node").alias("_n"), "comp")
    d = docs.select("doc_id", node().alias("_node")).join(comp, F.col("_node") == F.col("_n"), "left").select("doc_id", "_node", F.coalesce("comp", "_node").alias("_comp"))
    first = W.Window.partitionBy("_comp").orderBy(F.col("doc_id").asc_nulls_last(), "_node")
    best = materialise(d.withColumn("_at", F.row_number().over(first)).where("_at = 1").select(F.col("doc_id").alias("_id"), "_node"), "best")
    out = docs.withColumn("_own", node()).join(best.withColumnRenamed("_node", "_win"), (F.col("_own") == F.col("_win")) & F.col("doc_id").eqNullSafe(F.col("_id")), "left_semi")
    repeated = best.join(d, (d._node == best._node) & d.doc_id.eqNullSafe(best._id)).groupBy(best._node).count().where("count > 1")
    if repeated.isEmpty():
        return out.select(*docs.columns)
    return out.withColumn("_at", F.row_number().over(W.Window.partitionBy("_own", "doc_id").orderBy("doc_id"))).where("_at = 1").select(*docs.columns)
