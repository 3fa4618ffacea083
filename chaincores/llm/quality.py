"""Quality by ordinal cumulative-link regression on graded ratings.

One weight vector over hashed text features is shared by all grades: P(grade > k) = sigmoid(w.x - t_k) with
ordered thresholds t_1 < t_2 < ... A document's x is the mean over its words of the word's features (the word, its
shape, its last characters), so that the score is a mean of values per distinct word.
"""

from __future__ import annotations

import re
import tempfile
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import materialise, release
from .common import sums, word_codes

#: Labelled rows that a model is fitted on at most; they are drawn by a hash of the id.
SAMPLE, WIDTH, STEPS, RATE, DECAY = 5_000, 1 << 17, 100, 0.3, 1e-6
SCALE = 20.0
#: Pairs of a feature and its mean count that the driver holds at a time; the rest waits in a scratch file of its own.
PIECE = 1 << 21
_RUNS = ((re.compile(r"[a-z]+"), "a"), (re.compile(r"[A-Z]+"), "A"), (re.compile(r"[0-9]+"), "0"), (re.compile(r"[^\x00-\x7f]+"), "x"))


def word_features(word: str) -> tuple[int, int, int]:
    """Hashed features of a word: itself, its shape (runs of a class as one sign), its last three characters."""
    shape = word
    for run, sign in _RUNS:
        shape = run.sub(sign, shape)
    return tuple(zlib.crc32(f"{kind}{v}".encode()) % WIDTH for kind, v in (("w", word.lower()), ("s", shape), ("e", word[-3:])))


@dataclass
class OrdinalModel:
    """grades ascending; one threshold fewer than grades."""

    grades: np.ndarray
    weights: np.ndarray
    thresholds: np.ndarray

    def tails(self, score: np.ndarray) -> np.ndarray:
        """P(grade > k) for each threshold, as columns."""
        return 1 / (1 + np.exp(-np.clip(score[:, None] - self.thresholds[None, :], -40, 40)))

    def expected(self, tails: np.ndarray) -> np.ndarray:
        return self.grades[0] + tails @ np.diff(self.grades)


def fit_rows(y: np.ndarray, rows: list[tuple[np.ndarray, np.ndarray]], steps: int = STEPS, rate: float = RATE, decay: float = DECAY) -> OrdinalModel:
    """:func:`fit_flat` of ``rows`` (feature ids, mean counts)."""
    cat = lambda k, kind: np.concatenate([np.zeros(0, kind), *[r[k] for r in rows]])
    return fit_flat(y, cat(0, np.int64), cat(1, float), np.array([len(i) for i, _ in rows], np.int64), steps, rate, decay)


def fit_flat(y: np.ndarray, ids: np.ndarray, vals: np.ndarray, lens: np.ndarray, steps: int = STEPS, rate: float = RATE, decay: float = DECAY) -> OrdinalModel:
    """Maximum likelihood by full-batch Adam over rows of so many (feature, mean count) pairs. Thresholds are kept in order.

    Rows are gone through in pieces of about ``PIECE`` pairs, so ids and vals may lie in a file."""
    grades = np.unique(y).astype(float)
    if len(grades) < 2:
        return OrdinalModel(grades if len(grades) else np.array([1.0]), np.zeros(WIDTH), np.zeros(max(0, len(grades) - 1)))
    level, ends = np.searchsorted(grades, y), np.cumsum(lens)
    rows = np.unique([0, *(np.flatnonzero(np.diff(ends // PIECE)) + 1), len(lens)]).tolist()

    def piece(lo: int, hi: int) -> tuple:
        at = slice(int(ends[lo] - lens[lo]), int(ends[hi - 1]))
        return lo, hi, np.asarray(ids[at]), np.asarray(vals[at]) * SCALE, np.repeat(np.arange(hi - lo), lens[lo:hi])

    held = [piece(lo, hi) for lo, hi in zip(rows, rows[1:])] if len(rows) == 2 else None
    pieces = lambda: held or (piece(lo, hi) for lo, hi in zip(rows, rows[1:]))
    at_least = np.clip(np.array([(level > k).mean() for k in range(len(grades) - 1)]), 1e-3, 1 - 1e-3)
    w, t = np.zeros(WIDTH), -np.log(at_least / (1 - at_least))
    state = [np.zeros_like(w), np.zeros_like(w), np.zeros_like(t), np.zeros_like(t)]
    for step in range(1, steps + 1):
        s = np.concatenate([np.bincount(owner, v * w[i], hi - lo) for lo, hi, i, v, owner in pieces()])
        up = 1 / (1 + np.exp(-np.clip(s[:, None] - t[None, :], -40, 40)))
        p = np.concatenate([np.ones((len(s), 1)), up, np.zeros((len(s), 1))], 1)
        d = p * (1 - p)
        every = np.arange(len(s))
        own = np.maximum(p[every, level] - p[every, level + 1], 1e-9)  # P(grade = own level)
        g_s = -(d[every, level] - d[every, level + 1]) / own / len(s)
        g_t = np.zeros((len(s), len(grades) + 1))
        g_t[every, level] += d[every, level] / own / len(s)
        g_t[every, level + 1] -= d[every, level + 1] / own / len(s)
        g_w = sum(np.bincount(i, v * g_s[lo:hi][owner], WIDTH) for lo, hi, i, v, owner in pieces())
        grads = g_w + decay * w, g_t[:, 1:-1].sum(0)
        for k, (param, g) in enumerate(zip((w, t), grads, strict=True)):
            m, v = state[2 * k], state[2 * k + 1]
            m += 0.1 * (g - m)
            v += 0.01 * (g * g - v)
            param -= rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8) * (1.0 if k else 0.3)
        t[:] = np.maximum.accumulate(t + np.arange(len(t)) * 1e-9)
    return OrdinalModel(grades, w, t)


def sample_labels(labels: DataFrame, column: str, most: int) -> DataFrame:
    """``labels(doc_id, column)`` without nulls, one row per id (its largest), about ``most`` of them by a hash of the id."""
    one = labels.where(F.col(column).isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max(column).alias(column))
    n = one.count()
    share = F.lit(1 << 20) if n <= most else F.lit(int((1 << 20) * most / n))
    return one.where(F.pmod(F.xxhash64("doc_id", F.lit(99)), F.lit(1 << 20)) < share)


def fit(docs: DataFrame, labels: DataFrame, grade: str = "quality", most: int = SAMPLE) -> OrdinalModel:
    """Fit on whole texts of a bounded sample of the rated documents; the driver receives hashed counts, not texts, and a part at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            codes, words, counts = word_codes(b.column(1), lower=False)
            table = np.array([word_features(x) for x in words.to_pylist()], np.int32).reshape(-1, 3)
            out_i, out_v = [], []
            for s, e in zip(np.cumsum(counts) - counts, np.cumsum(counts), strict=True):
                ids, n = np.unique(table[codes[s:e]], return_counts=True)
                out_i.append(ids.tobytes())
                out_v.append((n / max(1, e - s)).astype(np.float32).tobytes())
            yield pa.record_batch([b.column(0), b.column(2), pa.array(out_i, pa.binary()), pa.array(out_v, pa.binary())], names=["doc_id", "y", "ids", "vals"])

    chosen = sample_labels(labels, grade, most)
    rated = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").select("doc_id", "text", F.col(grade).cast("double").alias("y"))
    counted = materialise(rated.mapInArrow(run, "doc_id long, y double, ids binary, vals binary"), "features")
    y, lens = [], []
    with tempfile.TemporaryFile() as f_i, tempfile.TemporaryFile() as f_v:
        for r in counted.orderBy("doc_id", "y", "ids", "vals").toLocalIterator():
            y.append(r.y)
            lens.append(len(r.ids) // 4)
            f_i.write(r.ids)
            f_v.write(r.vals)
        release(counted)
        if not sum(lens):
            return fit_flat(np.array(y), np.zeros(0, np.int32), np.zeros(0, np.float32), np.array(lens, np.int64))
        f_i.flush()
        f_v.flush()
        return fit_flat(np.array(y), np.memmap(f_i, np.int32, "r"), np.memmap(f_v, np.float32, "r"), np.array(lens, np.int64))


def score(docs: DataFrame, model: OrdinalModel) -> DataFrame:
    """All of ``docs`` and its columns, plus _expected (grade) and _tail, the probability of the top grade.

    Texts without words (null, empty) have only the thresholds to go by.
    """
    fields = docs.schema.names
    weights = model.weights.astype(np.float32)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[str, float] = {}
        for big in batches:
            for i in range(0, big.num_rows, 2000):
                b = big.slice(i, 2000)
                codes, words, counts = word_codes(b.column(fields.index("text")), lower=False)
                if len(known) > 500_000:
                    known.clear()
                values = np.empty(len(words))
                for k, x in enumerate(words.to_pylist()):
                    v = known.get(x)
                    if v is None:
                        v = known[x] = float(weights[list(word_features(x))].sum()) if x else 0.0
                    values[k] = v
                s = SCALE * sums(values[codes], counts) / np.maximum(counts, 1)
                tails = model.tails(s)
                top = tails[:, -1] if tails.shape[1] else np.ones(len(s))
                yield pa.record_batch([*b.columns, pa.array(model.expected(tails)), pa.array(top)], names=[*fields, "_expected", "_tail"])

    from pyspark.sql import types as T

    return docs.mapInArrow(run, T.StructType([*docs.schema.fields, T.StructField("_expected", T.DoubleType()), T.StructField("_tail", T.DoubleType())]))


def select(docs: DataFrame, labels: DataFrame, least: float = 0.5, grade: str = "quality", most: int = SAMPLE) -> DataFrame:
    """The rows of ``docs`` whose probability of the top grade is at least ``least``; columns as they were."""
    return score(docs, fit(docs, labels, grade, most)).where(F.col("_tail") >= least).select(*docs.columns)
