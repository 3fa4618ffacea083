"""External induced suffix sorting with common prefixes, recursive, vectorised by waves.

Suffixes are typed L or S. The S* suffixes (S after L) are sorted by the names of their S*-substrings: these names are a
string of their own, less than half as long, that the same procedure sorts. Sorted S* suffixes induce all L suffixes, and
these all S suffixes. Tuples (symbol, position, common prefix with the one before) wait in a disk-backed priority queue,
popped by symbol, and first in first out among equals. It pops a wave at a time: the longest run of tuples before which
nothing can be pushed any more, that is, whose symbols don't exceed the least symbol that the run itself pushes.

A pushed tuple's common prefix is one more than the minimum over its source and those since the last push of the same
symbol. Common prefixes are counted up to ``limit`` symbols. Arrays beyond the given memory are mapped to unnamed scratch files
of the task, which the system removes when it ends.
"""

from __future__ import annotations

import tempfile
from collections.abc import Callable, Iterator

import numpy as np

BATCH = 1 << 16
#: Bytes that the queues and each array of one sort may hold in memory.
MEMORY = 48 << 20
#: Ends a segment; no UTF-8 text has it.
END = 0xF8
RANGES = 256
_NONE = np.iinfo(np.int64).max


def room(n: int, dtype, memory: int) -> np.ndarray:
    """An array, mapped to a scratch file if it is larger than the memory."""
    return np.memmap(tempfile.TemporaryFile(), dtype, shape=(n,)) if n * np.dtype(dtype).itemsize > max(memory, 1) else np.empty(n, dtype)


class Symbols:
    """A string of bytes, or of names below ``size``, with comparison of many places at once."""

    def __init__(self, text: np.ndarray, size: int):
        self.n, self.size, self.text = len(text), size, text
        self.per, self.bits = (8, 8) if text.dtype == np.uint8 else (2, 32)  # symbols of a word
        if self.per == 8:
            self.padded = np.concatenate([text, np.zeros(16, np.uint8)])

    def words(self, at: np.ndarray) -> np.ndarray:
        """The symbols from each place as one number, first ones highest; what follows the end is undefined."""
        if self.per == 8:
            return np.lib.stride_tricks.sliding_window_view(self.padded, 8)[at].view(">u8")[:, 0].astype(np.uint64)
        one, last = np.uint64(1), self.n - 1  # the end is zero
        return ((self.text[np.minimum(at, last)].astype(np.uint64) + one) << np.uint64(32)) | (self.text[np.minimum(at + 1, last)].astype(np.uint64) + one)

    def common(self, a: np.ndarray, b: np.ndarray, limit: int) -> np.ndarray:
        """Common prefixes of suffixes, up to the limit."""
        out, live = np.zeros(len(a), np.int64), np.flatnonzero(np.maximum(a, b) < self.n)
        while len(live):
            x, y = a[live] + out[live], b[live] + out[live]
            diff, k = self.words(x) ^ self.words(y), np.zeros(len(live), np.int64)
            for i in range(1, self.per):
                k += diff < np.uint64(1 << (64 - self.bits * i))
            k = np.minimum(k + (diff == 0), self.n - np.maximum(x, y))
            out[live] += k
            live = live[(k == self.per) & (out[live] < limit) & (np.maximum(x, y) + k < self.n)]
        return np.minimum(out, limit)


class Queue:
    """A monotone priority queue of (symbol, position, common prefix), first in first out among equal symbols."""

    def __init__(self, size: int, memory: int = MEMORY):
        self.width = -(-size // RANGES)
        self.runs: list[list] = [[] for _ in range(RANGES)]
        self.memory, self.held, self.file = memory, 0, None

    def push(self, key: np.ndarray, pos: np.ndarray, lcp: np.ndarray) -> None:
        """Tuples in order of their symbols."""
        of = key // self.width
        cuts = [0, *(np.flatnonzero(of[1:] != of[:-1]) + 1).tolist(), len(of)] if len(of) else []
        for i, j in zip(cuts, cuts[1:]):
            self.runs[int(of[i])].append((key[i:j].astype(np.uint32), pos[i:j].astype(np.uint32), lcp[i:j].astype(np.uint16)))
            self.held += 10 * (j - i)
        if self.held > self.memory:
            self._spill()

    def _spill(self) -> None:
        if self.file is None:
            self.file = tempfile.TemporaryFile()
        self.file.seek(0, 2)
        for runs in self.runs:
            for i, run in enumerate(runs):
                if isinstance(run[0], np.ndarray):
                    runs[i] = (self.file.tell(), len(run[0]))
                    for part in run:
                        self.file.write(np.ascontiguousarray(part))
        self.held = 0

    def pop(self, r: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """All tuples of a range of symbols so far, by symbol; later pushes wait for the next pop."""
        runs, self.runs[r] = self.runs[r], []
        parts: list[list] = [[], [], []]
        for run in runs:
            if not isinstance(run[0], np.ndarray):
                at, n = run
                self.file.seek(at)
                run = tuple(np.frombuffer(self.file.read(n * size), kind) for size, kind in ((4, np.uint32), (4, np.uint32), (2, np.uint16)))
            else:
                self.held -= 10 * len(run[0])
            for p, x in zip(parts, run, strict=True):
                p.append(x)
        key, pos, lcp = (np.concatenate(p) if p else np.zeros(0, kind) for p, kind in zip(parts, (np.uint32, np.uint32, np.uint16), strict=True))
        if self.width > 1 and len(key):
            order = np.argsort(key, kind="stable")
            key, pos, lcp = key[order], pos[order], lcp[order]
        return key.astype(np.int64), pos.astype(np.int64), lcp.astype(np.int64)

    def close(self) -> None:
        if self.file is not None:
            self.file.close()


class Minima:
    """Common prefixes of pushes: per symbol, the minimum over the sources since its last push."""

    def __init__(self, size: int, limit: int, memory: int):
        self.tail, self.wave = room(size, np.int64, memory), room(size, np.int32, memory)
        self.wave[:] = -1  # number of the wave of the last push
        self.limit, self.now = limit, 0
        self.at, self.least = [], []  # waves whose minimum no later one undercuts, ascending

    def push(self, key: int) -> None:
        """A push without a source: nothing is common with what follows."""
        self.tail[key], self.wave[key] = 0, 0
        self.done(0)

    def done(self, least: int) -> None:
        while self.least and self.least[-1] >= least:
            self.least.pop()
            self.at.pop()
        self.least.append(least)
        self.at.append(self.now)
        self.now += 1

    def next(self, lcp: np.ndarray, key: np.ndarray, held: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For a wave of sources in order, some of which are ``held`` to push ``key``: (their order by symbol, prefixes)."""
        src = np.flatnonzero(held)
        k = key[src]
        order = np.argsort(k, kind="stable")
        src, k = src[order], k[order]
        heads = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]]))
        levels = [lcp]
        while (1 << len(levels)) <= len(lcp):
            w = 1 << (len(levels) - 1)
            levels.append(np.minimum(levels[-1][:-w], levels[-1][w:]))
        lo = np.concatenate([[0], src[:-1] + 1])
        lo[heads] = 0
        val = self._least(levels, lo, src)
        tops = k[heads]
        was = self.wave[tops]
        if self.at:  # what lies between that wave and this one
            after = np.searchsorted(self.at, was, "right")
            between = np.append(np.array(self.least, np.int64), self.limit)[np.minimum(after, len(self.least))]
        else:
            between = np.full(len(tops), self.limit, np.int64)
        val[heads] = np.where(was >= 0, np.minimum(np.minimum(val[heads], self.tail[tops]), between), -1)
        last = np.append(heads[1:], len(k)) - 1
        rest = src[last] + 1
        tail = np.full(len(rest), self.limit, np.int64)
        more = rest < len(lcp)
        if more.any():
            tail[more] = self._least(levels, rest[more], np.full(int(more.sum()), len(lcp) - 1))
        self.tail[tops], self.wave[tops] = tail, self.now
        return src, np.minimum(val + 1, self.limit)

    @staticmethod
    def _least(levels: list[np.ndarray], lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        j = np.frexp((hi - lo + 1).astype(np.float64))[1] - 1
        out = np.empty(len(lo), np.int64)
        for v in np.unique(j):
            at = j == v
            lv = levels[v]
            out[at] = np.minimum(lv[lo[at]], lv[hi[at] - (1 << int(v)) + 1])
        return out


def s_types(text: np.ndarray) -> np.ndarray:
    """True where the suffix is smaller than the next one; the last is L."""
    n = len(text)
    step = np.zeros(n, np.int8)
    step[:-1] = np.where(text[1:] > text[:-1], 1, np.where(text[1:] < text[:-1], -1, 0))
    step[-1] = -1
    at = np.where(step != 0, np.arange(n, dtype=np.int64), n)
    return step[np.minimum.accumulate(at[::-1])[::-1]] > 0


def name_substrings(s: Symbols, stars: np.ndarray) -> np.ndarray:
    """Ranks of the S*-substrings (from each star to the next, both included); equal ones share a rank.

    One that another begins with is the larger: there, the other goes on with an L. The last one meets the end, which is
    smaller than every symbol; it is a word longer here, so that the end is always looked at.
    """
    m, n = len(stars), s.n
    length = np.diff(np.append(stars, n - 1)) + 1
    length[-1] += s.per

    def chunk(i: np.ndarray, j: int) -> np.ndarray:
        left = np.clip(np.where(i == m - 1, n - stars[-1], length[i]) - s.per * j, 0, s.per)
        w = s.words(np.minimum(stars[i] + s.per * j, n - 1 if s.bits > 8 else n))
        short = left < s.per
        fill = np.where(short, (np.uint64(1) << (np.uint64(s.bits) * np.minimum(s.per - left, s.per - 1).astype(np.uint64))) - np.uint64(1), np.uint64(0))
        fill = np.where(left == 0, np.uint64(2**64 - 1), fill)
        return np.where(i == m - 1, w & ~fill, w | fill)

    key = chunk(np.arange(m), 0)
    order = np.argsort(key)
    new = np.ones(m, bool)
    new[1:] = key[order][1:] != key[order][:-1]
    j = 1
    while True:
        group = np.cumsum(new) - 1
        size = np.bincount(group)
        open_ = (size > 1) & (np.bincount(group, length[order] > s.per * j) > 0)
        at = np.flatnonzero(open_[group])
        if not len(at):
            break
        key = chunk(order[at], j)
        sub = np.lexsort((key, group[at]))
        order[at] = order[at][sub]
        g, k = group[at], key[sub]
        new[at[1:]] |= (g[1:] == g[:-1]) & (k[1:] != k[:-1])
        j += 1
    rank = np.empty(m, np.uint32)
    rank[order] = np.cumsum(new) - 1
    return rank


def double(name: np.ndarray, limit: int) -> tuple[np.ndarray, np.ndarray]:
    """For names that fit in memory: suffixes in ascending order up to ``limit`` names, and each one's common prefix with the one before.

    Ranks are the first place of a group of equals; each round looks twice as many names ahead, in open groups only.
    """
    m = len(name)
    order = np.argsort(name, kind="stable")
    g = name[order]
    heads = np.flatnonzero(np.concatenate([[True], g[1:] != g[:-1]]))
    size = np.diff(np.append(heads, m))
    rank = np.empty(m, np.int32)
    rank[order] = np.repeat(heads, size)
    at = np.flatnonzero(np.repeat(size, size) > 1)
    levels, step = [rank], 1
    while step < limit and len(at):
        own, g = order[at], rank[order[at]]
        nxt = own + step
        key = np.where(nxt < m, rank[np.minimum(nxt, m - 1)], -1)
        sub = np.argsort(g.astype(np.int64) * (m + 1) + (key + 1))
        own, key = own[sub], key[sub]
        order[at] = own
        head = np.flatnonzero(np.concatenate([[True], (g[1:] != g[:-1]) | (key[1:] != key[:-1])]))
        size = np.diff(np.append(head, len(at)))
        rank = rank.copy()
        rank[own] = np.repeat(at[head], size)
        levels.append(rank)
        at = at[np.repeat(size, size) > 1]
        step *= 2
    a, b = order[:-1].copy(), order[1:].copy()
    common = np.zeros(m, np.int64)
    alike = np.flatnonzero(levels[0][a] == levels[0][b])  # others have no name in common
    for j in range(len(levels) - 1, -1, -1):
        lv, x, y = levels[j], a[alike], b[alike]
        same = alike[(x < m) & (y < m) & (lv[np.minimum(x, m - 1)] == lv[np.minimum(y, m - 1)])]
        a[same] += 1 << j
        b[same] += 1 << j
        common[1 + same] += 1 << j
    return order, np.minimum(common, limit)


def sort_stars(s: Symbols, stars: np.ndarray, limit: int, memory: int) -> tuple[np.ndarray, np.ndarray]:
    """S* suffixes in ascending order, and each one's common prefix with the one before.

    Names that aren't all different are the string of the next level, which is sorted by induction as well if it doesn't fit in
    memory. What its suffixes have in common covers whole substrings; the rest lies within the first two that differ.
    """
    m = len(stars)
    if not m:
        return stars, np.zeros(0, np.int64)
    name = name_substrings(s, stars)
    kinds = int(name.max()) + 1
    if 64 * m <= memory:
        order, names = double(name, limit // 2 + 1)
    else:
        order, names = room(m, np.int64, memory), room(m, np.int64, memory)
    if 64 * m > memory and kinds == m:
        order[name], names[:] = np.arange(m), 0
    elif 64 * m > memory:
        to, before = m, None
        for pos, lcp in sorted_suffixes(Symbols(name, kinds), limit // 2 + 1, memory):  # stars lie two symbols apart at least
            order[to - len(pos) : to] = pos[::-1]
            # descending, a prefix is with the larger one: ascending it belongs to that
            if before is not None:
                names[to] = lcp[0]
            names[to - len(pos) + 1 : to] = lcp[:0:-1]
            to, before = to - len(pos), pos
        names[0] = 0
    out = room(m, np.int64, memory)
    out[0] = 0
    ends = np.append(stars, s.n)
    for i in range(1, m, 1 << 18):
        j = min(m, i + (1 << 18))
        a, b, q = np.asarray(order[i - 1 : j - 1]), np.asarray(order[i:j]), np.asarray(names[i:j])
        pa, pb = ends[np.minimum(a + q, m)], ends[np.minimum(b + q, m)]
        got = np.minimum(pb - stars[b], limit)
        short = np.flatnonzero(got < limit)
        got[short] += s.common(pa[short], pb[short], limit)
        out[i:j] = np.minimum(got, limit)
    return stars[order], out


def _sweep(s: Symbols, mirror: bool, want: np.ndarray, queue: Queue, minima: Minima, fixed: Callable, limit: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Waves (positions, common prefix with the one before, whether from the queue) of all sources in order of their symbols.

    ``mirror`` turns the order of symbols round. Per symbol, the queue's tuples come before ``fixed(range)``: symbols, positions
    and prefixes of sources that are known already. Each source pushes the position before it, if ``want`` has it.
    """
    prev_key, prev_pos, prev_queue = -1, -1, False
    size = s.size
    for r in range(RANGES):
        (qk, qp, ql), (fk, fp, fl) = queue.pop(r), fixed(r)
        if len(fk) and len(qk):
            order = np.argsort(np.concatenate([2 * qk, 2 * fk + 1]), kind="stable")
            comp, pos, lcp = np.concatenate([2 * qk, 2 * fk + 1])[order], np.concatenate([qp, fp])[order], np.concatenate([ql, fl])[order]
        else:
            comp, pos, lcp = (2 * qk, qp, ql) if len(qk) else (2 * fk + 1, fp, fl)
        while len(comp):
            c, p, v = comp[:BATCH], pos[:BATCH], lcp[:BATCH].copy()
            before = np.maximum(p - 1, 0)
            key = s.text[before].astype(np.int64)
            if mirror:
                key = size - 1 - key
            held = (p > 0) & want[before]
            least = np.minimum.accumulate(np.where(held, 2 * key, _NONE))
            late = np.flatnonzero(c[1:] > least[:-1])
            e = int(late[0]) + 1 if len(late) else len(c)
            c, p, v, key, held = c[:e], p[:e], v[:e], key[:e], held[:e]
            own, late_q = c >> 1, (c & 1) == 0
            first = np.concatenate([[own[0] != prev_key], own[1:] != own[:-1]])
            v[first] = 0
            meets = ~first & ~late_q & np.concatenate([[prev_queue], late_q[:-1]])
            if meets.any():
                at = np.flatnonzero(meets)
                v[at] = s.common(np.where(at > 0, p[np.maximum(at - 1, 0)], prev_pos), p[at], limit)
            prev_key, prev_pos, prev_queue = int(own[-1]), int(p[-1]), bool(late_q[-1])
            yield p, v, late_q
            if held.any():
                src, val = minima.next(v, key, held)
                queue.push(key[src], before[:e][src], val)
            minima.done(int(v.min()))
            comp, pos, lcp = comp[e:], pos[e:], lcp[e:]
            if queue.runs[r]:
                nk, np_, nl = queue.pop(r)
                if len(comp):
                    to = np.searchsorted(comp, 2 * nk, "right")
                    comp, pos, lcp = np.insert(comp, to, 2 * nk), np.insert(pos, to, np_), np.insert(lcp, to, nl)
                else:
                    comp, pos, lcp = 2 * nk, np_, nl


def sorted_suffixes(s: Symbols, limit: int, memory: int = MEMORY) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Batches (positions, common prefix with the one before) of all suffixes in descending order, prefixes up to ``limit`` symbols."""
    n = s.n
    if n == 0:
        return
    if limit > 65_535 or n >= 1 << 32:
        raise ValueError("positions take 32 bits, common prefixes 16")
    text, size = s.text, s.size
    small = s_types(text)
    stars = np.flatnonzero(small[1:] & ~small[:-1]) + 1
    order, prefix = sort_stars(s, stars, limit, memory)
    del stars
    first = text[order].astype(np.int64)
    queue, minima, kept = Queue(size, memory), Minima(size, limit, memory), Queue(size, memory)
    bounds = np.searchsorted(first, np.arange(RANGES + 1) * queue.width)

    def known_stars(r: int) -> tuple:
        i, j = bounds[r], bounds[r + 1]
        return first[i:j], np.asarray(order[i:j]).astype(np.int64), np.asarray(prefix[i:j])

    try:
        last = int(text[n - 1])
        queue.push(np.array([last]), np.array([n - 1]), np.array([0]))
        minima.push(last)
        for pos, lcp, queued in _sweep(s, False, ~small, queue, minima, known_stars, limit):
            at = np.flatnonzero(queued)
            if len(at):  # ascending, by symbol; ranges of the second pass run the other way
                kept.push(text[pos[at]].astype(np.int64), pos[at], lcp[at])
        queue.close()
        del order, prefix, first
        queue, minima = Queue(size, memory), Minima(size, limit, memory)
        # symbols turned round fall into other ranges: L suffixes come back as they are asked for
        pending: list[tuple] = []
        top = RANGES - 1

        def known_large(r: int) -> tuple:
            nonlocal top
            lo = size - 1 - ((r + 1) * queue.width - 1)  # symbols of this range, before the turn
            while top >= 0 and (top + 1) * kept.width - 1 >= lo:
                k, p, v = kept.pop(top)
                top -= 1
                if len(k):
                    # a prefix is with the one before in ascending order; descending it belongs to the smaller of the two
                    pending.append((k[::-1], p[::-1], np.concatenate([v[:0:-1], [0]])))
            out: list[tuple] = []
            while pending:
                k, p, v = pending.pop(0)
                j = int(np.searchsorted(-k, -lo, "right"))
                if j:
                    out.append((k[:j], p[:j], v[:j]))
                if j < len(k):
                    pending.insert(0, (k[j:], p[j:], v[j:]))
                    break
            if not out:
                return (np.zeros(0, np.int64),) * 3
            k, p, v = (np.concatenate(x) for x in zip(*out, strict=True))
            # the prefix of each with the larger one before it: that one's own value, one place further
            return size - 1 - k, p, np.concatenate([[0], v[:-1]])

        for pos, lcp, _ in _sweep(s, True, small, queue, minima, known_large, limit):
            yield pos, lcp
    finally:
        queue.close()
        kept.close()


def repeated(text: np.ndarray, length: int, memory: int = MEMORY) -> np.ndarray:
    """True at each position whose next ``length`` bytes also start at another position."""
    mark = np.zeros(len(text), bool)
    last = -1
    for pos, lcp in sorted_suffixes(Symbols(text, 256), length, memory):
        near = lcp >= length
        if near[0] and last >= 0:
            mark[last] = True
        mark[pos[near]] = True
        mark[pos[:-1][near[1:]]] = True
        last = int(pos[-1])
    return mark
