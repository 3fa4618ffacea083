"""String similarity."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType


def jaro_winkler(a: str, b: str) -> float:
    """Similarity in [0, 1]; a common prefix of up to four characters counts a tenth of the rest each, above 0.7."""
    if a == b:
        return 1.0
    if not a or not b:
        return 0.0
    reach = max(0, max(len(a), len(b)) // 2 - 1)
    used, left = [False] * len(b), []
    for i, ch in enumerate(a):
        for j in range(max(0, i - reach), min(len(b), i + reach + 1)):
            if not used[j] and b[j] == ch:
                used[j] = True
                left.append(ch)
                break
    m = len(left)
    if not m:
        return 0.0
    right = [ch for ch, u in zip(b, used, strict=True) if u]
    moved = sum(x != y for x, y in zip(left, right, strict=True)) // 2
    jaro = (m / len(a) + m / len(b) + (m - moved) / m) / 3
    if jaro <= 0.7:
        return jaro
    prefix = next((i for i in range(min(4, len(a), len(b))) if a[i] != b[i]), min(4, len(a), len(b)))
    return jaro + 0.1 * prefix * (1 - jaro)


#: Characters of a name beyond which a pair is compared by itself.
WIDE = 48


def jaro_winkler_many(a: list[str], b: list[str]) -> np.ndarray:
    """:func:`jaro_winkler` of many pairs at once, a pair of positions at a time."""
    out = np.zeros(len(a))
    wide = [i for i, (x, y) in enumerate(zip(a, b, strict=True)) if max(len(x), len(y)) > WIDE]
    for i in wide:
        out[i] = jaro_winkler(a[i], b[i])
    rest = np.setdiff1d(np.arange(len(a)), wide)
    for at in range(0, len(rest), 20_000):
        part = rest[at : at + 20_000]
        out[part] = _narrow([a[i] for i in part], [b[i] for i in part])
    return out


def _codes(names: list[str]) -> tuple[np.ndarray, np.ndarray]:
    size = np.fromiter(map(len, names), np.int64, len(names))
    wide = max(1, int(size.max()))
    return np.array(names, f"U{wide}").view(np.uint32).reshape(len(names), wide), size


def _narrow(a: list[str], b: list[str]) -> np.ndarray:
    (x, nx), (y, ny) = _codes(a), _codes(b)
    reach = np.maximum(0, np.maximum(nx, ny) // 2 - 1)
    left, right, far = np.zeros(x.shape, bool), np.zeros(y.shape, bool), int(reach.max())
    for i in range(x.shape[1]):
        free = i < nx
        for j in range(max(0, i - far), min(y.shape[1], i + far + 1)):
            hit = free & ~right[:, j] & (j < ny) & (abs(i - j) <= reach) & (x[:, i] == y[:, j])
            right[:, j] |= hit
            left[:, i] |= hit
            free &= ~hit
    m = left.sum(1)
    w = min(x.shape[1], y.shape[1])
    inner = np.take_along_axis(x, np.argsort(~left, 1, kind="stable"), 1)[:, :w] != np.take_along_axis(y, np.argsort(~right, 1, kind="stable"), 1)[:, :w]
    moved = (inner & (np.arange(w) < m[:, None])).sum(1) // 2
    some = np.maximum(m, 1)
    jaro = np.where(m > 0, (m / np.maximum(nx, 1) + m / np.maximum(ny, 1) + (m - moved) / some) / 3, 0.0)
    four = min(4, w)
    prefix = np.cumprod((x[:, :four] == y[:, :four]) & (np.arange(four) < np.minimum(nx, ny)[:, None]), 1).sum(1)
    same = np.fromiter((s == t for s, t in zip(a, b, strict=True)), bool, len(a))
    return np.where(same, 1.0, np.where(jaro <= 0.7, jaro, jaro + 0.1 * prefix * (1 - jaro)))


def _vector(a: pd.Series, b: pd.Series) -> pd.Series:
    held = (a.notna() & b.notna()).to_numpy()
    out = np.full(len(a), np.nan)
    out[held] = jaro_winkler_many(a[held].tolist(), b[held].tolist())
    return pd.Series(out).where(held, None)


def jaro_winkler_udf(a: Column, b: Column) -> Column:
    """Vectorised; null if either side is."""
    return F.pandas_udf(_vector, DoubleType())(a, b)


def _bag(name: str) -> list[tuple[str, int]]:
    """Characters with their occurrence number, so that sets of them count repetitions."""
    seen: Counter = Counter()
    out = []
    for ch in name:
        seen[ch] += 1
        out.append((ch, seen[ch]))
    return out


def _bits(bags: list[list[tuple[str, int]]], bit: dict[tuple[str, int], int]) -> tuple[np.ndarray, np.ndarray]:
    """A set of 64 bits for each bag, and how many of its members share the bit of another."""
    mask = np.zeros(len(bags), np.uint64)
    for k, bag in enumerate(bags):
        m = 0
        for t in bag:
            m |= bit[t]
        mask[k] = m
    return mask, np.fromiter(map(len, bags), np.int64, len(bags)) - np.bitwise_count(mask)


def _short_masks(names: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """As :func:`_bits` of the names' bags, a position at a time."""
    codes, size = _codes(names)
    wide = codes.shape[1]
    letter = np.unique(codes, return_inverse=True)[1].reshape(codes.shape)
    token, held = letter * wide, np.arange(wide) < size[:, None]
    for p in range(1, wide):
        token[:, p] += (letter[:, :p] == letter[:, p : p + 1]).sum(1)
    count = np.bincount(token[held])
    often = np.argsort(-count, kind="stable")[: np.count_nonzero(count)]
    at, bit = np.arange(len(often)), np.zeros(len(count), np.uint64)
    bit[often] = np.uint64(1) << np.where((len(often) <= 64) | (at < 48), at, 48 + at % 16).astype(np.uint64)
    mask = np.zeros(len(names), np.uint64)
    for p in range(wide):
        mask[held[:, p]] |= bit[token[held[:, p], p]]
    return mask, size - np.bitwise_count(mask)


def _masks(x: list[str], y: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Bits of the names of both lists, and how many of a name's characters share the bit of another."""
    names = x + y
    if max(map(len, names)) <= WIDE:
        return _short_masks(names)
    bags = [_bag(s) for s in names]
    often = [t for t, _ in Counter(t for bag in bags for t in bag).most_common()]
    return _bits(bags, {t: 1 << (k if len(often) <= 64 or k < 48 else 48 + k % 16) for k, t in enumerate(often)})


def _needed(nx: np.ndarray, ny: np.ndarray, prefix: int, threshold: float) -> np.ndarray:
    """Characters that names of these lengths and this common prefix have in common at least, if they are above the threshold.

    The last step decides ties by the arithmetic of :func:`jaro_winkler`, with no character moved."""
    nx, ny = np.maximum(nx, 1)[:, None], np.maximum(ny, 1)[None, :]
    least = threshold if threshold < 0.7 else max(0.7, (threshold - 0.1 * prefix) / (1 - 0.1 * prefix))
    m = np.maximum(1, np.ceil((3 * least - 1) * nx * ny / (nx + ny) - 1e-6))
    jaro = (m / nx + m / ny + 1.0) / 3
    best = np.where(jaro <= 0.7, jaro, jaro + 0.1 * prefix * (1 - jaro) + (1e-12 if prefix else 0.0))
    return (m + (best <= threshold)).astype(np.int32)


def _where(hit: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows and columns of the few true cells, eight cells of a row at a time; the row length is a multiple of eight."""
    some = np.flatnonzero(hit.view(np.uint64).ravel())
    at, k = np.nonzero(hit.reshape(-1, 8)[some])
    cell = some[at] * 8 + k
    return cell // hit.shape[1], cell % hit.shape[1]


#: Rows and columns of names that are compared at once, so that they stay near the processor.
HIGH, WIDTH = 32, 4096


def _alike(x: np.ndarray, y: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """For each key of both lists its positions in them, rising; negative keys are none."""
    held = []
    for z in (x, y):
        order = np.argsort(z, kind="stable")
        keys, first = np.unique(z[order], return_index=True)
        held.append({k: p for k, p in zip(keys.tolist(), np.split(order, first[1:]), strict=True) if k >= 0})
    for k, i in held[0].items():
        if k in held[1]:
            yield i, held[1][k]


def _candidates(x: list[str], y: list[str], within: bool, threshold: float) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Positions of all pairs that may be above the threshold: by common characters, and fewer of them where names begin alike."""
    mask, lost = _masks(x, [] if within else y)
    (mx, my), (lx, ly) = ((z, z) if within else (z[: len(x)], z[len(x) :]) for z in (mask, lost))
    (ux, ix), (uy, iy) = (np.unique([len(s) for s in z], return_inverse=True) for z in (x, y))
    need = [_needed(ux, uy, p, threshold) for p in range(5)]
    small = max(n.max() for n in need) < 250 and lx.max(initial=0) + 64 < 250 and ly.max(initial=0) + 64 < 250
    kind = np.uint8 if small else np.int32
    need, lx, ly = [n.astype(kind) for n in need], lx.astype(kind), ly.astype(kind)
    hx, hy = (np.array([[ord(c) for c in s[:4]] + [end] * (4 - len(s[:4])) for s in z], np.int64) for z, end in ((x, -1), (y, -2)))

    def common(i: np.ndarray, my: np.ndarray, ly: np.ndarray) -> np.ndarray:
        c = np.bitwise_count(mx[i, None] & my[None, :])
        return c.astype(kind, copy=False) + np.minimum(lx[i, None], ly[None, :]) if lx[i].any() and ly.any() else c.astype(kind, copy=False)

    def near(rows: np.ndarray, same: np.ndarray, least: np.ndarray, most: np.ndarray | None) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """Positions of pairs that have ``least`` characters in common, but not ``most``, and how many; those of a list before the diagonal aside.

        Columns are filled up to a multiple of eight with names of no character, which nothing has anything in common with."""
        j = np.concatenate([same, np.zeros(-len(same) % 8, np.int64)])
        m, low = my[j], ly[j]
        m[len(same) :], low[len(same) :] = 0, 0
        least, most = least[:, iy[j]], None if most is None else most[:, iy[j]]
        for at in range(0, len(rows), HIGH):
            i = rows[at : at + HIGH]
            for start in range(at - at % WIDTH if within else 0, len(j), WIDTH):
                part = slice(start, start + WIDTH)
                c = common(i, m[part], low[part])
                hit = c >= least[ix[i], part]
                if most is not None:
                    hit &= c < most[ix[i], part]
                a, b = _where(hit)
                yield i[a], j[b + start], c[a, b]

    for i, j, _ in near(np.arange(len(x)), np.arange(len(y)), need[0], None):
        yield i, j
    # names that begin with the same character, then those that do with the same two
    for i, j in _alike(hx[:, 0], hy[:, 0]):
        for a, b, _ in near(i, j, need[1], need[0]):
            yield a, b
    two = [np.where(h[:, 1] >= 0, (h[:, 0] << 21) + h[:, 1], end) for h, end in ((hx, -1), (hy, -2))]
    for i, j in _alike(*two):
        for a, b, c in near(i, j, need[4], need[1]):
            prefix = np.cumprod(hx[a] == hy[b], 1).sum(1)
            held = np.zeros(len(a), bool)
            for p in range(2, 5):
                held |= (prefix == p) & (c >= need[p][ix[a], iy[b]])
            yield a[held], b[held]


class _Places:
    """Where the names of a list have each character, as bits: :func:`jaro_winkler` of many pairs of positions at once."""

    def __init__(self, names: list[str]):
        codes, self.size = _codes(names)
        alphabet, letter = np.unique(codes, return_inverse=True)
        self.letter, self.letters = letter.reshape(codes.shape), len(alphabet)
        self.at = np.zeros(len(names) * self.letters, np.uint64)
        rows = np.arange(len(names)) * self.letters
        for j in range(codes.shape[1]):
            held = j < self.size
            self.at[rows[held] + self.letter[held, j]] |= np.uint64(1 << j)
        self.columns = np.ascontiguousarray(self.letter.T)
        # by reach and position: the positions that may match it
        self.window = np.array([[sum(1 << q for q in range(max(0, p - r), p + r + 1)) & (1 << 64) - 1 for r in range(codes.shape[1] // 2 + 1)] for p in range(codes.shape[1])], np.uint64)

    def above(self, i: np.ndarray, j: np.ndarray, threshold: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The pairs above the threshold, and their similarities."""
        one = np.uint64(1)
        nx, ny, wide = self.size[i], self.size[j], self.letter.shape[1]
        reach = np.maximum(0, np.maximum(nx, ny) // 2 - 1)
        row = j * self.letters
        left, right = np.zeros(len(i), np.uint64), np.zeros(len(i), np.uint64)
        shortest = int(nx.min(initial=0))
        for p in range(wide):
            free = self.at[row + self.columns[p][i]] & self.window[p][reach] & ~right
            if p >= shortest:
                free[p >= nx] = 0
            right |= free & (~free + one)
            left |= (free != 0).astype(np.uint64) << np.uint64(p)
        m = np.bitwise_count(left).astype(np.int64)
        four = min(4, wide)
        prefix = np.cumprod((self.letter[i, :four] == self.letter[j, :four]) & (np.arange(four) < np.minimum(nx, ny)[:, None]), 1).sum(1)

        def similarity(moved, m, nx, ny, prefix):
            some = np.maximum(m, 1)
            jaro = np.where(m > 0, (m / np.maximum(nx, 1) + m / np.maximum(ny, 1) + (m - moved) / some) / 3, 0.0)
            return np.where(jaro <= 0.7, jaro, jaro + 0.1 * prefix * (1 - jaro))

        # characters that moved lower it, so the others need no look at their order; a hair is left for rounding
        held = np.flatnonzero(similarity(0, m, nx, ny, prefix) > threshold - 1e-9)
        i, j, m, nx, ny, prefix, left, right = (z[held] for z in (i, j, m, nx, ny, prefix, left, right))
        moved = np.zeros(len(i), np.int64)
        for k in range(int(m.max(initial=0))):
            p, q = (np.bitwise_count((z & (~z + one)) - one) for z in (left, right))
            moved += (k < m) & (self.letter[i, np.minimum(p, wide - 1)] != self.letter[j, np.minimum(q, wide - 1)])
            left, right = left & (left - one), right & (right - one)
        sim = similarity(moved // 2, m, nx, ny, prefix)
        held = sim > threshold
        return i[held], j[held], sim[held]


#: Cells of the table of places, at most, and pairs that are compared at once.
PLACES, AT_ONCE = 8_000_000, 50_000


def pairs_above(x: list[str], y: list[str] | None, threshold: float) -> Iterator[tuple[list[str], list[str], np.ndarray]]:
    """(a, b, similarity) for all pairs a < b above the threshold between two lists of distinct names, or (y is None) within one."""
    within, waiting, n = y is None, [], 0
    if not x or not (within or y):
        return
    # the similarity depends on which name is first
    names = x if within else x + y
    rank = np.empty(len(names), np.int64)
    rank[sorted(range(len(names)), key=names.__getitem__)] = np.arange(len(names))
    # long names, and names of very many letters, are compared as texts
    short = max(map(len, names)) <= WIDE and (len(set().union(*names)) + 1) * len(names) <= PLACES
    places = _Places(names) if short else None

    def compare() -> tuple[list[str], list[str], np.ndarray]:
        i, j = (np.concatenate([w[c] for w in waiting]) + (c and not within and len(x)) for c in range(2))
        i, j = np.where(rank[i] < rank[j], (i, j), (j, i))
        if places:
            got = [places.above(i[at : at + AT_ONCE], j[at : at + AT_ONCE], threshold) for at in range(0, len(i), AT_ONCE)]
            i, j, sim = (np.concatenate([g[c] for g in got]) for c in range(3))
        else:
            sim = jaro_winkler_many([names[p] for p in i.tolist()], [names[q] for q in j.tolist()])
            held = np.flatnonzero(sim > threshold)
            i, j, sim = i[held], j[held], sim[held]
        return [names[p] for p in i.tolist()], [names[q] for q in j.tolist()], sim

    y = x if within else y
    for i, j in _candidates(x, y, within, threshold):
        if within:
            held = i < j
            i, j = i[held], j[held]
        waiting.append((i, j))
        n += len(i)
        if n > 200_000:
            yield compare()
            waiting, n = [], 0
    if n:
        yield compare()


def register(spark) -> None:
    """``jaro_winkler`` for SQL."""
    spark.udf.register("jaro_winkler", F.pandas_udf(_vector, DoubleType()))
