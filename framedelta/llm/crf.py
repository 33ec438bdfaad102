"""Linear-chain conditional random fields in numpy: exact forward-backward over many chains at once, and their fit.

Chains are laid out by position, longest first, so one step of the recursion handles that position of all chains in a few
array operations. Chains may have any length; nothing is cut or padded.
"""

from __future__ import annotations

import numpy as np


class Layout:
    """Where the items of chains with the given lengths (all > 0) lie when ordered by position."""

    def __init__(self, lengths: np.ndarray):
        self.lengths = np.asarray(lengths, np.int64)
        n = int(self.lengths.sum())
        order = np.argsort(-self.lengths, kind="stable")
        rank = np.empty(len(order), np.int64)
        rank[order] = np.arange(len(order))
        most = int(self.lengths.max(initial=0))
        ends = np.bincount(self.lengths, minlength=most + 1)
        self.active = (len(self.lengths) - np.cumsum(ends))[:most]  # chains longer than t
        self.off = np.concatenate([[0], np.cumsum(self.active)])
        starts = np.cumsum(self.lengths) - self.lengths
        t = np.arange(n) - np.repeat(starts, self.lengths)
        self.place = self.off[t] + np.repeat(rank, self.lengths)


def forward_backward(scores: np.ndarray, layout: Layout, transitions: np.ndarray, pairs: bool = False):
    """Marginals (n, K) in the order of scores; with pairs, also the log likelihood's normaliser and expected transitions (K, K)."""
    n, k = scores.shape
    if not n:
        return (np.zeros((0, k), scores.dtype), 0.0, np.zeros((k, k))) if pairs else np.zeros((0, k), scores.dtype)
    top = scores.max(1, keepdims=True)
    x = np.empty_like(scores)
    x[layout.place] = np.exp(scores - top)
    m = np.exp(transitions).astype(scores.dtype)
    alpha, off, act = np.empty_like(x), layout.off, layout.active
    log_z = float(top.sum())
    for t in range(len(act)):
        cur = x[off[t] : off[t + 1]]
        if t:
            cur = cur * (alpha[off[t - 1] : off[t - 1] + act[t]] @ m)
        total = cur.sum(1, keepdims=True)
        if pairs:
            log_z += float(np.log(total).sum())
        np.divide(cur, total, out=alpha[off[t] : off[t + 1]])
    beta = np.ones_like(x)
    expected = np.zeros((k, k))
    for t in range(len(act) - 1, 0, -1):
        after = x[off[t] : off[t + 1]] * beta[off[t] : off[t + 1]]
        here = slice(off[t - 1], off[t - 1] + act[t])
        b = after @ m.T
        if pairs:
            joint = alpha[here][:, :, None] * m[None] * after[:, None, :]
            expected += (joint / joint.sum((1, 2), keepdims=True)).sum(0)
        beta[here] = b / b.sum(1, keepdims=True)
    marg = alpha * beta
    marg /= marg.sum(1, keepdims=True)
    marg = marg[layout.place]
    return (marg, log_z, expected) if pairs else marg


class Bags:
    """Items that are types (`of`), each of which has a bag of features (`flat`, cut at `starts`; no bag is empty)."""

    def __init__(self, of: np.ndarray, flat: np.ndarray, starts: np.ndarray, size: int):
        self.of, self.flat, self.starts, self.size = of, flat, starts, size
        self.owner = np.repeat(np.arange(len(starts)), np.diff(np.append(starts, len(flat))))

    def scores(self, w: np.ndarray) -> np.ndarray:
        return np.add.reduceat(w[self.flat], self.starts, axis=0)[self.of]

    def push(self, g: np.ndarray) -> np.ndarray:
        types = np.stack([np.bincount(self.of, g[:, k], len(self.starts)) for k in range(g.shape[1])], 1)
        return np.stack([np.bincount(self.flat, types[self.owner, k], self.size) for k in range(g.shape[1])], 1)


def fit(items, y: np.ndarray, lengths: np.ndarray, labels: int, steps: int = 40, rate: float = 0.15, l2: float = 1e-5, start: np.ndarray | None = None, max_transition: float = 3.0):
    """Weights (features, labels) and transitions that maximise the labels' conditional likelihood, by Adam on all chains."""
    w = np.zeros((items.size, labels)) if start is None else start.astype(float)
    t = np.zeros((labels, labels))
    layout, n = Layout(lengths), len(y)
    gold = np.zeros((n, labels))
    gold[np.arange(n), y] = 1
    ends = np.cumsum(lengths)
    inner = np.ones(n, bool)
    inner[ends - 1] = False
    at = np.flatnonzero(inner)
    seen = np.zeros((labels, labels))
    np.add.at(seen, (y[at], y[at + 1]), 1)
    state = [np.zeros_like(x) for x in (w, w, t, t)]
    for i in range(1, steps + 1):
        marg, _, expected = forward_backward(items.scores(w), layout, t, pairs=True)
        grads = (items.push(gold - marg) / n - l2 * w, (seen - expected) / n - l2 * t)
        for j, (p, g) in enumerate(zip((w, t), grads, strict=True)):
            state[2 * j] = 0.9 * state[2 * j] + 0.1 * g
            state[2 * j + 1] = 0.99 * state[2 * j + 1] + 0.01 * g * g
            p += rate * (state[2 * j] / (1 - 0.9**i)) / (np.sqrt(state[2 * j + 1] / (1 - 0.99**i)) + 1e-8)
        np.clip(t, -max_transition, max_transition, out=t)
    return w, t
