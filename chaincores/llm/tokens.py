"""Token counts by a compiled finite-state transducer.

Merging by rank leaves a sequence of pieces exactly when each piece, and each two neighbours, merge to themselves: a first
merge across a border would also be made between these two alone. So the last piece of a text's tokens is the one that
ends there, stays whole, and stays apart from the last piece before it; and the tokens of a text up to the start of that
piece are those of the text so far. What later characters need of the past is finite: for each place
from which the characters since begin some piece, the last piece before that place, and how many tokens lie between.
That is a state; a character leads to one next state and emits the change of the number of tokens, which may be below
zero where a longer piece takes the place of shorter ones. States and transitions are compiled from the vocabulary when
first met. Two characters that no piece holds side by side lead back to the first state.

A chunk's map takes a state to a state and a number. All but a few states agree soon, so the map is that of the first state,
and what the first characters of the chunk make of any other one: if they lead to the same state, the rest is the same. Maps
compose associatively; the chunks of a long text are mapped in other tasks, and put together by a parallel prefix scan.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from functools import lru_cache
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import sums, utf8

MARK = "▁".encode()
#: Bytes of a chunk; of a text beyond which its chunks go to tasks of their own; characters in which states should agree.
CHUNK, LONG, HEAD = 1 << 20, 8 << 20, 256
#: States beyond which a worker starts anew, between batches of texts.
STATES = 250_000


class Map(NamedTuple):
    """What a chunk does: ``head`` is to be run from any state; if that ends in ``sync``, ``count`` more tokens and state
    ``end`` follow, else what ``body`` says: texts to be run, and maps to be followed. Without ``sync`` the head is all."""

    head: str
    sync: tuple | None = None
    count: int = 0
    end: tuple | None = None
    body: tuple = ()


class Transducer:
    """Counts of a sentencepiece BPE model with byte fallback, identity normalisation and a dummy prefix."""

    def __init__(self, path: str):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        self.score: dict[str, float] = {}
        self.trie: list[dict[str, int]] = [{}]
        self.piece_at: dict[int, str] = {}
        self.side_by_side: set[str] = set()
        for i in range(model.get_piece_size()):
            if model.is_byte(i) or model.is_control(i) or model.is_unknown(i):
                continue
            if model.is_unused(i):
                raise ValueError("unused pieces are not compiled")
            piece = model.id_to_piece(i).replace("▁", " ")
            self.score[piece] = model.get_score(i)
            at = 0
            for c in piece:
                if c not in self.trie[at]:
                    self.trie[at][c] = len(self.trie)
                    self.trie.append({})
                at = self.trie[at][c]
            self.piece_at[at] = piece
            self.side_by_side.update(map("".join, zip(piece, piece[1:])))
        if any(p[i] == " " != p[i - 1] for p in self.score for i in range(1, len(p))) or any("\n" in p for p in self.score):
            raise ValueError("a piece crosses a unit boundary")
        self.whole: dict[str, bool] = {}
        self.reset()

    def reset(self) -> None:
        self.apart: dict[tuple[str, str], bool] = {}
        self.ids: dict[tuple, int] = {}
        self.keys: list[tuple] = []
        self.next: list[dict[str, tuple[int, int]]] = []
        self.state(("", ((0, None, 0),)))

    def state(self, key: tuple) -> int:
        """Number of a state, given as (last character, ((trie node since a place, last piece before it, tokens since), ...))."""
        at = self.ids.get(key)
        if at is None:
            at = self.ids[key] = len(self.keys)
            self.keys.append(key)
            self.next.append({})
        return at

    def merge(self, text: str) -> list[str]:
        """Pieces of a short text: the best-ranked neighbours merge first, the left ones of equals."""
        parts = list(text)
        while True:
            best, at = None, -1
            for i in range(len(parts) - 1):
                s = self.score.get(parts[i] + parts[i + 1])
                if s is not None and (best is None or s > best):
                    best, at = s, i
            if best is None:
                return parts
            parts[at : at + 2] = [parts[at] + parts[at + 1]]

    def stays_whole(self, piece: str) -> bool:
        if (known := self.whole.get(piece)) is None:
            known = self.whole[piece] = self.merge(piece) == [piece]
        return known

    def stay_apart(self, left: str | None, right: str) -> bool:
        if left is None or left[-1] + right[0] not in self.side_by_side:
            return True
        if (known := self.apart.get((left, right))) is None:
            known = self.apart[left, right] = self.merge(left + right) == [left, right]
        return known

    def step(self, state: int, c: str) -> tuple[int, int]:
        """Compile the transition of a state on a character."""
        last, places = self.keys[state]
        if last + c not in self.side_by_side:
            places = ((0, None, 0),)
        found, kept = None, []
        for at, before, since in places:
            to = self.trie[at].get(c)
            if to is not None:
                kept.append((to, before, since))
                piece = self.piece_at.get(to)
            else:
                piece = c if at == 0 else None  # of no piece: its bytes
            if piece is not None and self.stays_whole(piece) and self.stay_apart(before, piece):
                found = piece, since
        if found is None and places[-1][1:] != (None, 0):
            raise AssertionError("no piece ends here")
        piece, since = found or (c, 0)
        emitted = (1 if piece in self.score else len(c.encode())) - since
        key = c, (*((to, before, n + emitted) for to, before, n in kept), (0, piece, 0))
        done = self.next[state][c] = self.state(key), emitted
        return done

    def run(self, text: str, state: int = 0) -> tuple[int, int]:
        """(state after a text, tokens emitted)."""
        n, step = 0, self.next
        for c in text:
            to = step[state].get(c) or self.step(state, c)
            state = to[0]
            n += to[1]
        return state, n

    def map(self, text: str) -> Map:
        """The map of a chunk; it keeps the body only if nothing in the head makes all states agree."""
        head, body = text[:HEAD], text[HEAD:]
        if not body:
            return Map(head)
        sync, _ = self.run(head)
        end, n = self.run(body, sync)
        sure = any(a + b not in self.side_by_side for a, b in zip(head, head[1:]))
        return Map(head, self.keys[sync], n, self.keys[end], () if sure else (body,))

    def follow(self, key: tuple, m: Map) -> tuple[tuple, int]:
        """(state, tokens) of a map after the state ``key``."""
        state, n = self.run(m.head, self.state(key))
        key = self.keys[state]
        if m.sync is None:
            return key, n
        if key == m.sync:
            return m.end, n + m.count
        for part in m.body:
            if isinstance(part, Map):
                key, more = self.follow(key, part)
            else:
                state, more = self.run(part, self.state(key))
                key = self.keys[state]
            n += more
        return key, n

    def compose(self, x: Map, y: Map) -> Map:
        """The map of one chunk and then the next."""
        if x.sync is None:
            x = self.map(x.head + y.head)
            if y.sync is None:
                return x
            y = y._replace(head="")
        end, n = self.follow(x.end, y)
        return Map(x.head, x.sync, x.count + n, end, x.body and (*x.body, y))

    def scan(self, maps: list[Map]) -> list[Map]:
        """Maps of all prefixes: neighbours compose, then every second prefix is known, and gives the others."""
        if len(maps) < 2:
            return maps
        pairs = self.scan([self.compose(maps[i], maps[i + 1]) for i in range(0, len(maps) - 1, 2)])
        return [maps[0], *(pairs[i // 2] if i % 2 else self.compose(pairs[i // 2 - 1], maps[i]) for i in range(1, len(maps)))]

    def total(self, maps: list[Map]) -> int:
        """Tokens of a whole text."""
        return self.follow(self.keys[0], self.scan(maps)[-1])[1] if maps else 0

    def count(self, data: bytes, chunk: int = CHUNK) -> int:
        """Tokens of one text of any length, chunk by chunk."""
        return self.total([self.map(x) for x in pieces(data, chunk)])

    def count_many(self, texts: list[bytes], chunk: int = CHUNK) -> np.ndarray:
        """Tokens of each text; short texts are cut where the transducer is in its first state, and each distinct unit runs once."""
        if len(self.keys) > STATES:
            self.reset()
        out = np.zeros(len(texts), np.int64)
        short: list[int] = []
        for i, t in enumerate(texts):
            if len(t) > chunk:
                out[i] = self.count(t, chunk)
            elif t:
                short.append(i)
        if short:
            parts = [prepared(texts[i]) for i in short]
            b = np.frombuffer(data := b"\n".join(parts) + b"\n", np.uint8)  # a newline after each text: one token more
            at = np.concatenate([[0], unit_starts(b), [len(b)]]).astype(np.int64)
            units = pa.LargeStringArray.from_buffers(len(at) - 1, pa.py_buffer(at), pa.py_buffer(data)).dictionary_encode()
            emitted = np.array([self.run(u)[1] for u in units.dictionary.to_pylist()], np.int64)[np.asarray(units.indices)]
            ends = np.searchsorted(at[:-1], np.cumsum([len(p) + 1 for p in parts]))
            out[short] = sums(emitted, np.diff(ends, prepend=0)) - 1
        return out


def prepared(data: bytes) -> bytes:
    """A text with its dummy prefix, marks as blanks; nothing for an empty one."""
    return b" " + data.replace(MARK, b" ") if data else b""


def pieces(data: bytes, chunk: int) -> Iterator[str]:
    """The prepared text in chunks of about so many bytes, whole characters each."""
    data, at = prepared(data), 0
    while at < len(data):
        to = min(at + chunk, len(data))
        while to < len(data) and data[to] & 0xC0 == 0x80:
            to += 1
        yield data[at:to].decode()
        at = to


def unit_starts(b: np.ndarray) -> np.ndarray:
    """Places (from 1 on) before which no piece reaches: blanks after others, and around newlines."""
    blank, line = b == 32, b == 10
    return np.flatnonzero((blank[1:] & ~blank[:-1]) | line[1:] | line[:-1]) + 1


@lru_cache(2)
def transducer(path: str) -> Transducer:
    """One per Python worker."""
    return Transducer(path)


def token_counts(docs: DataFrame, model: str, limit: int = 4096, long: int = LONG, chunk: int = CHUNK) -> DataFrame:
    """``docs(doc_id, text)`` -> doc_id, n_bytes, n_tokens, over_limit; one row per row, null text is empty (0 tokens).

    Texts of more than ``long`` bytes are cut to chunks, which are mapped where they are dealt to, and composed per text.
    """

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = transducer(model)
        for batch in batches:
            for i in range(0, batch.num_rows, 2000):
                part = batch.slice(i, 2000)
                texts = utf8(part.column(1))
                yield pa.record_batch([part.column(0), pa.array([len(x) for x in texts], pa.int64()), pa.array(t.count_many(texts))], names=["doc_id", "n_bytes", "n_tokens"])

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, text in enumerate(utf8(b.column(1))):
                for k, piece in enumerate(pieces(text, chunk)):
                    yield pa.record_batch([b.column(0).slice(i, 1), b.column(2).slice(i, 1), pa.array([len(text)], pa.int64()), pa.array([k], pa.int32()), pa.array([piece], pa.string())], names=["doc_id", "key", "n_bytes", "at", "piece"])

    def mapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = transducer(model)
        for b in batches:
            for i in range(b.num_rows):
                m = pickle.dumps(t.map(b.column(4)[i].as_py()))
                yield pa.record_batch([*(c.slice(i, 1) for c in b.columns[:4]), pa.array([m], pa.binary())], names=["doc_id", "key", "n_bytes", "at", "map"])

    def composed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = transducer(model)
        for b in batches:
            n = [t.total([pickle.loads(m) for m in maps]) for maps in b.column(2).to_pylist()]
            yield pa.record_batch([b.column(0), b.column(1), pa.array(n, pa.int64())], names=["doc_id", "n_bytes", "n_tokens"])

    large = F.coalesce(F.octet_length("text") > long, F.lit(False))
    out = docs.where(~large).select("doc_id", "text").mapInArrow(count, "doc_id long, n_bytes long, n_tokens long")
    cuts = docs.where(large).select("doc_id", "text", F.md5("text").alias("key")).mapInArrow(cut, "doc_id long, key string, n_bytes long, at int, piece string")
    maps = cuts.repartition("key", "at").mapInArrow(mapped, "doc_id long, key string, n_bytes long, at int, map binary")
    # equal rows give equal maps: one of each place counts, as often as there are rows
    maps = maps.groupBy("doc_id", "key", "n_bytes", "at").agg(F.first("map").alias("map"), F.count("*").alias("rows"))
    maps = maps.groupBy("doc_id", "key", "n_bytes").agg(F.array_sort(F.collect_list(F.struct("at", "map"))).alias("m"), F.first("rows").alias("rows"))
    maps = maps.withColumn("again", F.explode(F.sequence(F.lit(1), F.col("rows")))).select("doc_id", "n_bytes", F.col("m.map").alias("m"))
    out = out.unionByName(maps.mapInArrow(composed, "doc_id long, n_bytes long, n_tokens long"))
    return out.withColumn("over_limit", F.col("n_tokens") > limit)
