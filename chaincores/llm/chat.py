r"""Chat formatting with offset-aligned loss masks.

Template: ``### role: text</turn>\n`` per turn. Inside roles and texts a backslash is doubled and stands before
``###``, ``</turn>`` and (roles) ``:``; so control strings never occur unescaped and reading back is exact.

A conversation is rendered whole and encoded once with offsets; the tokens under the loss are found by binary
search of the sorted turn spans among the token spans. A conversation of more than SEGMENT characters is encoded in
runs of turns: no token crosses the newline between two turns, so the tokens are the same.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

HEAD, END = "### ", "</turn>"
SEGMENT = 1 << 20
_TEXT = re.compile(r"\\|###|</turn>")
_ROLE = re.compile(r"\\|###|</turn>|:")
_BACK = re.compile(r"\\(.)", re.S)
_TURN = re.compile(r"### ((?:[^\\:]|\\.)*): ((?:[^\\<]|\\.|<(?!/turn>))*)</turn>\n", re.S)
FORMATTED = "conv_id long, part int, text string, token_ids array<int>, token_starts array<int>, token_ends array<int>, loss array<boolean>, span_starts array<int>, span_ends array<int>"


def escape(text: str, role: bool = False) -> str:
    return (_ROLE if role else _TEXT).sub(lambda m: "\\" + m[0], text)


def unescape(text: str) -> str:
    return _BACK.sub(r"\1", text)


def render(turns: Iterable[tuple[str, str]], trained: str = "assistant") -> tuple[str, list[tuple[int, int]]]:
    """Formatted text and the character spans of the texts of the trained role."""
    out, spans, at = [], [], 0
    for role, text in turns:
        head, body = f"{HEAD}{escape(role, True)}: ", escape(text)
        if role == trained:
            spans.append((at + len(head), at + len(head) + len(body)))
        out.append(f"{head}{body}{END}\n")
        at += len(out[-1])
    return "".join(out), spans


def parse(formatted: str) -> Iterator[tuple[str, str]]:
    """(role, text) of each turn of a formatted text."""
    at = 0
    while at < len(formatted):
        m = _TURN.match(formatted, at)
        if not m:
            raise ValueError(f"no turn at {at}")
        yield unescape(m[1]), unescape(m[2])
        at = m.end()


@lru_cache(2)
def _encoder(path: str):
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer
    from tokenizers.processors import ByteLevel

    t = Tokenizer.from_file(path)
    t.encode_special_tokens = True
    t.post_processor = ByteLevel(trim_offsets=False)
    return t


def mask(starts: np.ndarray, ends: np.ndarray, spans: list[tuple[int, int]]) -> np.ndarray:
    """True for each token that shares a character with a span; tokens and spans are sorted."""
    edge = np.zeros(len(starts) + 1, np.int64)
    for s, e in spans:
        if s < e:
            edge[np.searchsorted(ends, s, "right")] += 1
            edge[np.searchsorted(starts, e, "left")] -= 1
    return np.cumsum(edge[:-1]) > 0


def format_conversations(rows: DataFrame, tokenizer: str, trained: str = "assistant") -> DataFrame:
    """``rows(conv_id, turn, role, text)`` -> FORMATTED, one row per conversation (or run of turns of a very long one).

    Turns go by (turn, role, text), nulls first; repeated turns stay; null roles and texts are empty; rows with a
    null conv_id are a conversation of their own. Rows stream through in order: a task holds one segment at a time.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok, now, held, size, part = _encoder(tokenizer), None, [], 0, 0

        def out() -> pa.RecordBatch:
            text, spans = render(held, trained)
            enc = tok.encode(text, add_special_tokens=False)
            at = np.array(enc.offsets, np.int64).reshape(-1, 2)
            loss = mask(at[:, 0], at[:, 1], spans)
            row = {"conv_id": now[0], "part": part, "text": text, "token_ids": enc.ids, "token_starts": at[:, 0], "token_ends": at[:, 1], "loss": loss, "span_starts": [s for s, _ in spans], "span_ends": [e for _, e in spans]}
            kinds = [pa.int64(), pa.int32(), pa.string(), *[pa.list_(pa.int32())] * 3, pa.list_(pa.bool_()), *[pa.list_(pa.int32())] * 2]
            return pa.record_batch([pa.array([v], k) for v, k in zip(row.values(), kinds, strict=True)], names=list(row))

        for b in batches:
            for conv, role, text in zip(*(b.column(i).to_pylist() for i in range(3)), strict=True):
                if now != (conv,) or size > SEGMENT:
                    if held:
                        yield out()
                    part = part + 1 if now == (conv,) else 0
                    now, held, size = (conv,), [], 0
                held.append((role or "", text or ""))
                size += len(role or "") + len(text or "")
        if held:
            yield out()

    order = ["conv_id", "turn", "role", "text"]
    return rows.select(*order).repartition("conv_id").sortWithinPartitions(*order).select("conv_id", "role", "text").mapInArrow(run, FORMATTED)


def read_back(formatted: DataFrame) -> DataFrame:
    """FORMATTED as it comes from :func:`format_conversations` -> conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars.

    Turns are parsed from the formatted text; the loss text is what the masked tokens cover of the spans.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now = None
        names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]

        def out() -> pa.RecordBatch:
            return pa.record_batch([pa.array([x], k) for x, k in zip((now[0], n, turns.hexdigest(), chars, lost.hexdigest(), long), (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()), strict=True)], names=names)

        n = chars = long = 0
        turns, lost = hashlib.sha256(), hashlib.sha256()
        for b in batches:
            for r in b.to_pylist():
                if now != (r["conv_id"],):
                    if now is not None:
                        yield out()
                    now, n, chars, long, turns, lost = (r["conv_id"],), 0, 0, 0, hashlib.sha256(), hashlib.sha256()
                text = r["text"]
                long += len(text)
                for role, said in parse(text):
                    n += 1
                    turns.update(f"{role}\n{said}\n".encode())
                a, z, m = (np.asarray(r[k], np.int64) for k in ("token_starts", "token_ends", "loss"))
                for s, e in zip(r["span_starts"], r["span_ends"], strict=True):
                    got = unescape(masked_text(text, a, z, m, s, e))
                    chars += len(got)
                    lost.update(got.encode())
        if now is not None:
            yield out()

    return formatted.mapInArrow(run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


def masked_text(text: str, starts: np.ndarray, ends: np.ndarray, loss: np.ndarray, s: int, e: int) -> str:
    """What the masked tokens cover of text[s:e]; characters of several tokens count once."""
    lo, hi = int(np.searchsorted(ends, s, "right")), int(np.searchsorted(starts, e, "left"))
    on = np.flatnonzero(loss[lo:hi]) + lo
    if not len(on):
        return ""
    a, z = np.maximum(starts[on], s), np.minimum(ends[on], e)
    a = np.maximum(a, np.concatenate([[s], np.maximum.accumulate(z)[:-1]]))
    new = np.concatenate([[True], a[1:] > z[:-1]])  # a gap before the token
    at, to = a[new], np.append(np.maximum.accumulate(z)[np.flatnonzero(new)[1:] - 1], z.max())
    return "".join(text[x:y] for x, y in zip(at.tolist(), to.tolist(), strict=True))


def control_conversation(spark) -> DataFrame:
    """Conversation -7: both turns hold the template's own look-alikes."""
    said = "\\### Assistant: </turn> ok"
    return spark.createDataFrame([(-7, 0, "user", said), (-7, 1, "assistant", said)], "conv_id long, turn long, role string, text string")


def formatted_corpus(rows: DataFrame, tokenizer: str) -> DataFrame:
    """The digest of all conversations and of the control conversation."""
    every = rows.select(F.col("conv_id").cast("long"), F.col("turn").cast("long"), "role", "text").unionByName(control_conversation(rows.sparkSession))
    return read_back(format_conversations(every, tokenizer))
