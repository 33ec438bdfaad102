"""Document quality from its lines: a linear-chain conditional random field calls each line good or bad.

A line's features are shares of byte classes, lengths, repetition within the line and of the line, each cut into bins learned from the
sample; the same features of the line before and the line after count too. Forward-backward gives each line's probability
to be good; their mean, weighted by the lines' lengths, is the text's raw quality. A logistic curve through the
sample's labels turns that, and the share of weight in lines that are surely bad, into the score.

Labels belong to texts, so lines start with the label of their text. After a first fit the lines of bad texts which look good take that
label, and a second fit follows.

The fit uses a bounded sample (`per_label` texts of each label) on the driver; prediction reads all texts. Features are computed over the
bytes of a whole Arrow batch at once.

Defined cases: null and empty texts are one empty line and get the score which that has. Without labels of both kinds there is nothing to
learn, and all scores are the share of label 1 (0.5 without labels). Repeated rows, null ids and extra columns change nothing.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import map_text, raw_texts
from .crf import Layout, fit, forward_backward
from .langid_crf import labelled

BINS = 8
CLASSES = 8
BAD, GOOD = 0, 1


def _class_table() -> np.ndarray:
    """Byte to class: 0 space, 1 lower, 2 upper, 3 digit, 4 sentence mark, 5 symbol, 6 beyond ASCII, 7 other."""
    t = np.full(256, 7, np.int64)
    t[[9, 11, 12, 13, 32]] = 0
    t[97:123], t[65:91], t[48:58], t[128:] = 1, 2, 3, 6
    t[[ord(c) for c in ".,;:?'\"()-"]] = 4
    t[[ord(c) for c in "#*$%&|<>!@^_=+~{}[]\\/"]] = 5
    return t


TABLE = _class_table()
STEP = np.uint64(0x9E3779B97F4A7C15)  # odd, so its powers have inverses


def line_features(rows: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(features (lines, m), bytes of each line, lines of each text)."""
    buf = np.frombuffer(b"\n".join(rows) + b"\n", np.uint8)
    ends = np.flatnonzero(buf == 10)
    starts = np.append(0, ends[:-1] + 1)
    size = (ends - starts).astype(np.int64)
    n_lines = np.array([t.count(b"\n") + 1 for t in rows], np.int64)
    doc = np.repeat(np.arange(len(rows)), n_lines)
    cls = TABLE[buf]
    cls[ends] = CLASSES  # line ends are of no class
    line = np.repeat(np.arange(len(ends)), size + 1)
    counts = np.bincount(line * (CLASSES + 1) + cls, minlength=len(ends) * (CLASSES + 1)).reshape(-1, CLASSES + 1)[:, :CLASSES]
    # words: runs of bytes which are neither space nor line end, each hashed by a polynomial over its bytes
    inside = (cls != 0) & (cls != CLASSES)
    edge = np.diff(inside.astype(np.int8), prepend=0)
    w0, w1 = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    with np.errstate(over="ignore"):
        power = np.cumprod(np.full(len(buf), STEP, np.uint64))
        run = np.cumsum(buf.astype(np.uint64) * power)
        total = run[w1 - 1] - np.where(w0 > 0, run[w0 - 1], np.uint64(0))
        inverse = np.cumprod(np.full(len(buf), np.uint64(pow(int(STEP), -1, 1 << 64)), np.uint64))
        word = total * inverse[w0]
        whole = (run[ends - 1 + (size == 0)] - np.where(starts > 0, run[starts - 1], np.uint64(0))) * inverse[np.minimum(starts, len(buf) - 1)]
    of = line[w0] if len(w0) else np.empty(0, np.int64)
    n_words = np.bincount(of, minlength=len(ends))
    same = np.zeros(len(w0), bool)
    same[1:] = (word[1:] == word[:-1]) & (of[1:] == of[:-1])
    last = np.flatnonzero(np.append(of[1:] != of[:-1], True)) if len(of) else np.empty(0, np.int64)
    repeats = np.bincount(of[same], minlength=len(ends))
    marked = np.bincount(of, (cls[w1 - 1] == 5), minlength=len(ends)) if len(w0) else np.zeros(len(ends))
    shouted = np.bincount(of, (cls[w0] == 2) & (cls[np.minimum(w0 + 1, len(buf) - 1)] == 2), minlength=len(ends)) if len(w0) else np.zeros(len(ends))
    alone = np.bincount(of, (w1 - w0 == 1) & (cls[w0] == 5), minlength=len(ends)) if len(w0) else np.zeros(len(ends))
    ended = np.zeros(len(ends))
    ended[of[last]] = cls[w1[last] - 1] == 4
    # distinct words of a text over its words; lines seen before in the text
    key = np.stack([doc[of], word.view(np.int64)]) if len(w0) else np.empty((2, 0), np.int64)
    order = np.lexsort(key[::-1])
    fresh = np.append(True, (np.diff(key[:, order]) != 0).any(0)) if len(order) else np.empty(0, bool)
    per_doc = np.bincount(key[0], minlength=len(rows))
    variety = np.bincount(key[0][order], fresh, minlength=len(rows)) / np.maximum(per_doc, 1)
    key = np.stack([doc, whole.view(np.int64)])
    order = np.lexsort((np.arange(len(ends)), key[1], key[0]))
    again = np.zeros(len(ends))
    again[order[1:]] = ((np.diff(key[:, order]) == 0).all(0)) & (size[order[1:]] > 0)
    full = np.maximum(size, 1)[:, None]
    per_word = np.maximum(n_words, 1)
    x = np.column_stack([counts / full, np.log1p(size), np.log1p(n_words), (size - counts[:, 0]) / per_word, repeats / per_word, marked / per_word, shouted / per_word, alone / per_word, ended, variety[doc], again, np.log1p(n_lines[doc])])
    return x, size, n_lines


def features_in_parts(rows: list[bytes], most: int = 1 << 20) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """line_features of about `most` bytes of texts at a time: its arrays by byte are many times the text."""
    parts, at, run = [], 0, 0
    for i, t in enumerate(rows):
        run += len(t)
        if run >= most or i + 1 == len(rows):
            parts.append(line_features(rows[at : i + 1]))
            at, run = i + 1, 0
    return tuple(np.concatenate(x) for x in zip(*parts, strict=True)) if parts else line_features(rows)


class Binned:
    """Items of m features in bins, with those of both neighbours: a weight for each place, feature, bin and label."""

    def __init__(self, x: np.ndarray, n_lines: np.ndarray, cuts: list[np.ndarray]):
        m = x.shape[1]
        own = np.stack([np.searchsorted(cuts[j], x[:, j], "right") + (BINS + 1) * j for j in range(m)], 1)
        block = (BINS + 1) * m
        ends = np.cumsum(n_lines)
        before, after = np.full_like(own, -1), np.full_like(own, -1)
        before[1:], after[:-1] = own[:-1] + block, own[1:] + 2 * block
        before[ends - n_lines], after[ends - 1] = 3 * block, 3 * block  # no neighbour
        self.idx = np.concatenate([own, before, after], 1)
        self.size = 3 * block + 1

    def scores(self, w: np.ndarray) -> np.ndarray:
        out = w[self.idx[:, 0]].copy()
        for j in range(1, self.idx.shape[1]):
            out += w[self.idx[:, j]]
        return out

    def push(self, g: np.ndarray) -> np.ndarray:
        flat = self.idx.ravel()
        return np.stack([np.bincount(flat, np.repeat(g[:, k], self.idx.shape[1]), self.size) for k in range(g.shape[1])], 1)


class Model:
    def __init__(self, cuts, weights, transitions, curve):
        self.cuts, self.weights, self.transitions, self.curve = cuts, weights, transitions, curve

    def lines(self, rows: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(probability that each line is good, its bytes, lines of each text)."""
        x, size, n = features_in_parts(rows)
        return forward_backward(Binned(x, n, self.cuts).scores(self.weights), Layout(n), self.transitions)[:, GOOD], size, n

    def texts(self, rows: list[bytes]) -> np.ndarray:
        """(mean log odds of the texts' weighted line quality, weighted share of surely bad lines)."""
        good, size, n = self.lines(rows)
        doc = np.repeat(np.arange(len(rows)), n)
        weight = size + 1.0
        total = np.bincount(doc, weight, len(rows))
        mean = np.clip(np.bincount(doc, weight * good, len(rows)) / total, 1e-6, 1 - 1e-6)
        return np.column_stack([np.log(mean / (1 - mean)), np.bincount(doc, weight * (good < 0.1), len(rows)) / total])

    def score(self, rows: list[bytes]) -> np.ndarray:
        if self.cuts is None:
            return np.full(len(rows), self.curve[0])
        z = np.column_stack([self.texts(rows), np.ones(len(rows))]) @ self.curve
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def logistic(x: np.ndarray, y: np.ndarray, l2: float = 1e-3, steps: int = 50, weight: np.ndarray | None = None) -> np.ndarray:
    """Weights of a logistic regression (last: intercept) by Newton steps; `weight` tells how much each row counts."""
    x = np.column_stack([x, np.ones(len(x))])
    v = np.ones(len(x)) if weight is None else weight * len(x) / weight.sum()
    w = np.zeros(x.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (v * (p - y)) / len(y) + l2 * w
        h = (x * (v * p * (1 - p))[:, None]).T @ x / len(y) + l2 * np.eye(len(w))
        step = np.linalg.solve(h, g)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return w


def bin_cuts(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Up to BINS - 1 cuts: quantiles of all lines and of the bad texts' lines, which may be rare."""
    q = np.linspace(0, 1, BINS // 2 + 1)[1:-1]
    both = [np.quantile(v, q) for v in (x, x[y == BAD]) if len(v)]
    return np.unique(np.concatenate(both))[: BINS - 1]


def learn(sample: list[tuple[str, int, float]], steps: int = 40) -> Model:
    """Fit to (text, label 0 or 1, weight). The field sees each label as often as the sample; the scores' curve sees the table's shares of labels."""
    y_doc = np.array([int(y) for _, y, _ in sample], np.int64)
    weight = np.array([v for *_, v in sample], float)
    if len(set(y_doc.tolist())) < 2:
        return Model(None, None, None, [float(y_doc.mean()) if len(y_doc) else 0.5])
    rows = [t.encode() for t, *_ in sample]
    x, _, n = features_in_parts(rows)
    cuts = [bin_cuts(x[:, j], y_doc[np.repeat(np.arange(len(rows)), n)]) for j in range(x.shape[1])]
    cuts = [np.append(c, np.full(BINS - len(c), np.inf)) for c in cuts]
    items = Binned(x, n, cuts)
    doc = np.repeat(np.arange(len(rows)), n)
    y = y_doc[doc]
    w, t = fit(items, y, n, 2, steps=steps, l2=1e-4)
    good = forward_backward(items.scores(w), Layout(n), t)[:, GOOD]
    looks = (y == BAD) & (good > 0.8)
    rest = np.bincount(doc, (y == BAD) & ~looks, len(rows)) > 0  # a bad text keeps a bad line
    y2 = np.where(looks & rest[doc], GOOD, y)
    w, t = fit(items, y2, n, 2, steps=steps, l2=1e-4)
    model = Model(cuts, w, t, None)
    model.curve = logistic(model.texts(rows), y_doc, weight=weight)
    return model


def fitted(docs: DataFrame, labels: DataFrame, may: Column, label: str = "quality", per_label: int = 1500) -> Model:
    """Learn from about per_label labelled texts of each label among the rows that `may` allows."""
    return learn(labelled(docs, labels, may, label, {0: per_label, 1: per_label}))


def predict(docs: DataFrame, model: Model, threshold: float = 0.3, carry: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The carried columns, score double and predicted int."""
    carry = tuple(c for c in carry if c not in ("score", "predicted"))
    types = dict(docs.dtypes)
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(b: pa.RecordBatch) -> pa.RecordBatch:
        s = sent.value.score(raw_texts(b.column("text")))
        done = [pa.array(s, pa.float64()), pa.array((s >= threshold).astype(np.int32), pa.int32())]
        return pa.RecordBatch.from_arrays([*(b.column(c) for c in carry), *done], [*carry, "score", "predicted"])

    return map_text(docs.select(*dict.fromkeys([*carry, "text"])), run, ", ".join([*(f"`{c}` {types[c]}" for c in carry), "score double, predicted int"]))
