"""A bidirectional gated recurrent network with attention pooling, in numpy.

A word's input is a hashed word vector beside the mean of its hashed character trigrams. The network reads windows of
words in both directions, weighs the states by attention and gives one logit per window; a document's logit is
that of its strongest window. Training follows the strongest window of each document.
"""

from __future__ import annotations

import zlib

import numpy as np

BUCKETS, WORD, CHAR, HIDDEN, ATTEND = 1 << 14, 8, 8, 8, 8
WINDOW, STRIDE = 32, 16
MIN_STEPS = 250
F32 = np.float32


def word_inputs(word: bytes) -> tuple[int, list[int]]:
    """Bucket of a lower-cased word and the buckets of its character trigrams."""
    edged = b"<" + word + b">"
    h = zlib.crc32
    return h(word) % BUCKETS, [h(edged[i : i + 3]) % BUCKETS for i in range(len(edged) - 2)]


def windows(counts: np.ndarray, window: int = WINDOW, stride: int = STRIDE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For texts of so many words: each window's text, first word (over all texts) and length. Every text has a window."""
    n = np.maximum(1, -(-np.maximum(counts - window, 0) // stride) + 1)
    owner = np.repeat(np.arange(len(counts)), n)
    k = np.arange(len(owner)) - np.repeat(np.cumsum(n) - n, n)
    return owner, np.repeat(np.cumsum(counts) - counts, n) + k * stride, np.minimum(window, counts[owner] - k * stride)


def _sig(x: np.ndarray) -> np.ndarray:
    return F32(0.5) + F32(0.5) * np.tanh(F32(0.5) * x)


class Network:
    def __init__(self, seed: int = 1):
        rng = np.random.default_rng(seed)
        d, h = WORD + CHAR, HIDDEN
        mat = lambda *s: rng.normal(0, 1 / np.sqrt(s[0]), s).astype(F32)
        self.p = {"word": rng.normal(0, 0.1, (BUCKETS, WORD)).astype(F32), "char": rng.normal(0, 0.3, (BUCKETS, CHAR)).astype(F32), "A": mat(2 * h, ATTEND), "a": np.zeros(ATTEND, F32), "v": mat(ATTEND), "o": mat(2 * h), "b": np.zeros(1, F32)}
        for s in "fb":
            self.p |= {"W" + s: mat(d, 3 * h), "c" + s: np.zeros(3 * h, F32), "U" + s: mat(h, 3 * h)}

    def inputs(self, words: list[tuple[int, list[int]]]) -> np.ndarray:
        """Input vectors of distinct words."""
        x = np.zeros((len(words), WORD + CHAR), F32)
        if words:
            x[:, :WORD] = self.p["word"][[w for w, _ in words]]
            n = np.array([len(t) for _, t in words])
            flat = np.fromiter((i for _, t in words for i in t), np.int64, int(n.sum()))
            total = np.add.reduceat(self.p["char"][flat], np.cumsum(n) - n) if len(flat) else 0
            x[:, WORD:] = total / n[:, None]
        return x

    def gates(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The input's part of all gates, for both directions; the last row is for padding."""
        pad = np.zeros((1, x.shape[1]), F32)
        return tuple(np.concatenate([x, pad]) @ self.p["W" + s] + self.p["c" + s] for s in "fb")

    def _read(self, g: np.ndarray, m: np.ndarray, side: str, keep: bool):
        """States of one direction: g (time, rows, 3h), m (time, rows, 1)."""
        h, u_ = HIDDEN, self.p["U" + side]
        out, memo = np.empty((g.shape[0], g.shape[1], h), F32), []
        state = np.zeros((g.shape[1], h), F32)
        for t in range(g.shape[0]) if side == "f" else range(g.shape[0] - 1, -1, -1):
            u = state @ u_
            zr = _sig(g[t, :, : 2 * h] + u[:, : 2 * h])
            z, r = zr[:, :h], zr[:, h:]
            n = np.tanh(g[t, :, 2 * h :] + r * u[:, 2 * h :])
            new = n + z * (state - n)
            new = state + m[t] * (new - state)
            if keep:
                memo.append((t, state, u[:, 2 * h :], z, r, n))
            out[t] = state = new
        return out, memo

    def forward(self, gf: np.ndarray, gb: np.ndarray, index: np.ndarray, lengths: np.ndarray, keep: bool = False):
        """Logits of windows: index (rows, time) into the gate tables, padded beyond the lengths."""
        at = index.T
        m = (np.arange(at.shape[0])[:, None] < lengths[None, :]).astype(F32)[:, :, None]
        hf, mf = self._read(gf[at], m, "f", keep)
        hb, mb = self._read(gb[at], m, "b", keep)
        states = np.concatenate([hf, hb], 2)
        q = np.tanh(states @ self.p["A"] + self.p["a"])
        s = np.where(m[:, :, 0] > 0, q @ self.p["v"], F32(-1e9))
        e = np.exp(s - s.max(0)) * m[:, :, 0]
        alpha = e / np.maximum(e.sum(0), F32(1e-20))
        pooled = np.einsum("tn,tnh->nh", alpha, states)
        logit = pooled @ self.p["o"] + self.p["b"][0]
        return (logit, (at, m, mf, mb, states, q, alpha, pooled)) if keep else logit

    def backward(self, memo, dlogit: np.ndarray) -> tuple[dict, np.ndarray, np.ndarray]:
        """Gradients of the parameters, and of the gate inputs of both directions (time, rows, 3h)."""
        at, m, mf, mb, states, q, alpha, pooled = memo
        h, grad = HIDDEN, {}
        grad["o"], grad["b"] = dlogit @ pooled, np.array([dlogit.sum()], F32)
        dc = dlogit[:, None] * self.p["o"]
        da = np.einsum("nh,tnh->tn", dc, states)
        dstates = alpha[:, :, None] * dc[None]
        ds = alpha * (da - (alpha * da).sum(0))
        dq = ds[:, :, None] * self.p["v"] * (1 - q * q)
        grad["v"] = np.einsum("tn,tnk->k", ds, q)
        grad["A"], grad["a"] = np.einsum("tnh,tnk->hk", states, dq), dq.sum((0, 1))
        dstates += dq @ self.p["A"].T
        out = []
        for side, steps, part in (("f", mf, dstates[:, :, :h]), ("b", mb, dstates[:, :, h:])):
            dg, du_all, carry = np.zeros((*at.shape, 3 * h), F32), np.zeros((h, 3 * h), F32), 0
            for t, before, un, z, r, n in reversed(steps):
                d = part[t] + carry
                on = d * m[t]
                dn = on * (1 - z) * (1 - n * n)
                dz, dr = on * (before - n) * z * (1 - z), dn * un * r * (1 - r)
                du = np.concatenate([dz, dr, dn * r], 1)
                dg[t] = np.concatenate([dz, dr, dn], 1)
                du_all += before.T @ du
                carry = on * z + d * (1 - m[t]) + du @ self.p["U" + side].T
            grad["U" + side] = du_all
            out.append(dg)
        return grad, out[0], out[1]


def window_index(codes: np.ndarray, first: np.ndarray, lengths: np.ndarray, pad: int) -> np.ndarray:
    at = first[:, None] + np.arange(WINDOW)[None, :]
    inside = np.arange(WINDOW)[None, :] < lengths[:, None]
    return np.where(inside, codes[np.minimum(at, max(len(codes) - 1, 0))] if len(codes) else pad, pad)


def score_texts(net: Network, x: np.ndarray, codes: np.ndarray, counts: np.ndarray, block: int = 1024) -> tuple[np.ndarray, np.ndarray]:
    """Largest logit of each text over all its windows, and the number of that window."""
    owner, first, lengths = windows(counts)
    gf, gb = net.gates(x)
    logit = np.empty(len(owner), F32)
    for i in range(0, len(owner), block):
        logit[i : i + block] = net.forward(gf, gb, window_index(codes, first[i : i + block], lengths[i : i + block], len(x)), lengths[i : i + block])
    starts = np.flatnonzero(np.diff(owner, prepend=-1))
    best = np.maximum.reduceat(logit, starts) if len(starts) else np.zeros(0, F32)
    hit = np.flatnonzero(logit == best[owner])
    return best, hit[np.searchsorted(owner[hit], np.arange(len(counts)))] if len(starts) else np.zeros(0, np.int64)


def train(words: list[tuple[int, list[int]]], codes: np.ndarray, counts: np.ndarray, y: np.ndarray, epochs: int = 5, batch: int = 128, rate: float = 0.02, seed: int = 1) -> Network:
    """Fit to document labels (0/1) by Adam; embeddings by their own Adam on the rows in use."""
    net, rng = Network(seed), np.random.default_rng(seed)
    owner, first, lengths = windows(counts)
    w_ids = np.array([w for w, _ in words], np.int64)
    n_tri = np.array([len(t) for _, t in words])
    tri = np.fromiter((i for _, t in words for i in t), np.int64, int(n_tri.sum()))
    tri_owner = np.repeat(np.arange(len(words)), n_tri)
    state = {k: (np.zeros_like(v), np.zeros_like(v)) for k, v in net.p.items()}
    step = 0
    batch = min(batch, max(16, len(y) // 50))
    epochs = max(epochs, -(-MIN_STEPS * batch // max(1, len(y))))  # few documents are read more often
    for epoch in range(epochs):
        _, chosen = score_texts(net, net.inputs(words), codes, counts)
        if epoch == 0:  # nothing is learnt yet: any window of the text
            chosen = (rng.random(len(counts)) * np.bincount(owner, minlength=len(counts))).astype(np.int64) + np.searchsorted(owner, np.arange(len(counts)))
        order = rng.permutation(len(y))
        for i in range(0, len(order), batch):
            docs = order[i : i + batch]
            w = chosen[docs]
            index = window_index(codes, first[w], lengths[w], len(words))
            used, local = np.unique(index, return_inverse=True)
            local = local.reshape(index.shape)
            real = used[used < len(words)]
            x = net.inputs([words[k] for k in real])
            local = np.where(index == len(words), len(real), local)
            gf, gb = net.gates(x)
            logit, memo = net.forward(gf, gb, local, lengths[w], keep=True)
            d = ((1 / (1 + np.exp(-logit)) - y[docs]) / len(docs)).astype(F32)
            grad, df, db = net.backward(memo, d)
            flat = local.T.ravel()
            dx = np.zeros((len(real) + 1, WORD + CHAR), F32)
            for side, dg in (("f", df), ("b", db)):
                dg = dg.reshape(-1, 3 * HIDDEN)
                xs = np.concatenate([x, np.zeros((1, x.shape[1]), F32)])
                on = flat < len(real)
                grad["W" + side], grad["c" + side] = xs[flat].T @ dg, dg[on].sum(0)
                np.add.at(dx, flat, dg @ net.p["W" + side].T)
            dw, dc = np.zeros_like(net.p["word"]), np.zeros_like(net.p["char"])
            np.add.at(dw, w_ids[real], dx[:-1, :WORD])
            place = np.full(len(words), -1)
            place[real] = np.arange(len(real))
            mine = place[tri_owner] >= 0
            np.add.at(dc, tri[mine], (dx[:-1, WORD:] / n_tri[real][:, None])[place[tri_owner[mine]]])
            grad["word"], grad["char"] = dw, dc
            step += 1
            for k, g in grad.items():
                m, v = state[k]
                m += F32(0.1) * (g - m)
                v += F32(0.01) * (g * g - v)
                net.p[k] -= (rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-7)).astype(F32)
    return net
