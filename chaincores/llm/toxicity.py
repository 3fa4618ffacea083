"""Toxicity of documents by the recurrent network of :mod:`gru`, over all overlapping windows of the whole text."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import gru
from .common import spread, word_codes
from .quality import sample_labels

#: Labelled documents of each class that the network is fitted on at most, drawn by a hash of the id.
PER_CLASS, KEEP, EPOCHS = 1_500, 400_000, 5
#: Characters of a text that the network learns from at most, in evenly spaced pieces; all of every text is scored.
LEARN = 16_384


def held_out(doc_id="doc_id"):
    """True for the fifth of the ids that no model may learn from."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 5 == 0, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame, label: str = "toxic", per_class: int = PER_CLASS, epochs: int = EPOCHS) -> tuple[gru.Network, float]:
    """Network and the shift of its logit from the sample's share of positives to that of all labelled rows."""
    known = labels.where(~held_out()).where(F.col(label).isin(0, 1)).select("doc_id", label)
    share = {r[label]: r["count"] for r in known.groupBy(label).count().collect()}
    if len(share) < 2:
        net = gru.Network()
        net.p["o"][:] = 0
        return net, 4.0 if 1 in share else -4.0
    drawn = sample_labels(known.where(f"{label} = 1"), label, per_class).unionByName(sample_labels(known.where(f"{label} = 0"), label, 2 * per_class))
    got = docs.select("doc_id", "text").join(F.broadcast(drawn), "doc_id").select("doc_id", spread(F.col("text"), LEARN).alias("text"), F.col(label).cast("int").alias("y")).toArrow().sort_by([("doc_id", "ascending"), ("y", "ascending")]).combine_chunks()
    if not len(got):
        return gru.Network(), 0.0
    codes, words, counts = word_codes(got["text"].combine_chunks())
    y = np.asarray(got["y"]).astype(np.float32)
    net = gru.train([gru.word_inputs(w.encode()) for w in words.to_pylist()], codes, counts, y, epochs)
    odds = lambda a, b: np.log((a + 1) / (b + 1))
    return net, float(odds(share[1], share[0]) - odds(y.sum(), (1 - y).sum()))


def scores(docs: DataFrame, net: gru.Network, shift: float = 0.0) -> DataFrame:
    """``docs(doc_id, text)`` -> doc_id, held_out, score, predicted, n_windows; one row per row.

    Null and empty texts have one empty window, which only the network's bias speaks for. Null ids count as not held out.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place: dict[str, int] = {}
        table = np.zeros((0, gru.WORD + gru.CHAR), np.float32)
        for big in batches:
            for i in range(0, big.num_rows, 1000):
                b = big.slice(i, 1000)
                codes, words, counts = word_codes(b.column(2))
                listed = words.to_pylist()
                if len(place) > KEEP:
                    place, table = {}, table[:0]
                new = [w for w in listed if w not in place]
                if new:
                    for w in new:
                        place[w] = len(place)
                    table = np.concatenate([table, net.inputs([gru.word_inputs(w.encode()) for w in new])])
                x = table[np.fromiter((place[w] for w in listed), np.int64, len(listed))]
                logit, _ = gru.score_texts(net, x, codes, counts)
                p = 1 / (1 + np.exp(-(logit.astype(np.float64) + shift)))
                n = np.bincount(gru.windows(counts)[0], minlength=len(counts))
                yield pa.record_batch([b.column(0), b.column(1), pa.array(p), pa.array((p >= 0.5).astype(np.int32)), pa.array(n, pa.int64())], names=["doc_id", "held_out", "score", "predicted", "n_windows"])

    return docs.select("doc_id", held_out().alias("held_out"), "text").mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int, n_windows long")
