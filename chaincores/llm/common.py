"""Shared pieces of the text operators."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = UPPER.lower()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ascii_lower(c: Column) -> Column:
    """Lower-case A-Z only, whatever the locale or script."""
    return F.translate(c, UPPER, LOWER)


def n_words(c: Column) -> Column:
    """Number of runs of other than ASCII white space; 0 for null."""
    return F.coalesce(F.regexp_count(c, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def spread(text: Column, most: int, pieces: int = 8) -> Column:
    """A text of up to ``most`` characters as it is; of a longer one, so many in evenly spaced pieces: for samples that models learn from."""
    n, size = F.char_length(text), most // pieces
    some = F.concat_ws(" ", F.transform(F.sequence(F.lit(0), F.lit(pieces - 1)), lambda i: F.substring(text, 1 + F.floor(i * (n - size) / (pieces - 1)).cast("int"), F.lit(size))))
    return F.when(n > most, some).otherwise(text)


def utf8(column: pa.Array) -> list[bytes]:
    """UTF-8 bytes of each text; null is empty."""
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]


_BLANK = np.zeros(256, bool)
_BLANK[[0x20, *range(0x09, 0x0E)]] = True


def word_codes(column: pa.Array, lower: bool = True) -> tuple[np.ndarray, pa.Array, np.ndarray]:
    """Words (ASCII white space apart) of a batch: codes of all occurrences, distinct words, and words per text."""
    texts = utf8(column)
    b = np.frombuffer(b"\n".join([*texts, b""]), np.uint8)
    if not len(b):
        return np.zeros(0, np.int64), pa.array([], pa.large_string()), np.zeros(len(texts), np.int64)
    if lower:
        b = np.where((b >= 65) & (b <= 90), b + np.uint8(32), b)
    blank = _BLANK[b]
    held = ~blank
    starts = np.flatnonzero(held & np.concatenate([[True], blank[:-1]]))
    ends = np.flatnonzero(blank & np.concatenate([[False], held[:-1]]))
    offsets = np.concatenate([[0], np.cumsum(ends - starts)]).astype(np.int64)
    data = np.ascontiguousarray(b[held])
    words = pa.LargeStringArray.from_buffers(len(starts), pa.py_buffer(offsets), pa.py_buffer(data)).dictionary_encode()
    upto = np.searchsorted(starts, np.cumsum([len(t) + 1 for t in texts]))
    return np.asarray(words.indices).astype(np.int64), words.dictionary, np.diff(upto, prepend=0)


def sums(values: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Sum of ``values`` over consecutive runs of ``counts`` lengths (0 for empty runs)."""
    total = np.concatenate([np.zeros((1, *values.shape[1:]), values.dtype), np.cumsum(values, axis=0)])
    ends = np.cumsum(counts)
    return total[ends] - total[ends - counts]
