"""Language of every word by a linear-chain conditional random field, and of every text by the sum of its words.

A chain is the words of a line: runs of letters, lower-cased. A word's features are its affixes, its letter n-grams and whether it
is in the lexicon of the most frequent words of the fit; a weight for each feature and language and one for each
pair of neighbouring languages are learned together. Forward-backward gives the probabilities of each word's language, so
a line may change its language, as code-switched text does. The fit sees such lines: lines of different languages are
joined for it. A text's language has most probability, summed over words and weighted by letters; its share is the score.

The fit uses a bounded sample, whose bounds are parameters (`docs_per_lang`, `train_words`); it runs on the driver. Prediction
reads all texts. Scores of words are kept in a bounded table per worker. The n-grams of many words
are cut and looked up at once, as numbers.

Defined cases: null texts and texts without letters are `und` with score 0. Null languages are not learned from. If there is nothing
to learn from, all texts are `und`. Words are of at least one letter; marks, digits and number signs divide them. Of equal sums the alphabetically first language wins. Extra columns are ignored.
"""

from __future__ import annotations

import random
import re
import uuid
from collections import Counter
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import map_text, texts, worker_state
from .crf import Bags, Layout, fit, forward_backward

WORD = re.compile(r"[^\W\d_]+")
#: Words whose scores a worker keeps, and how many words are scored at a time.
KNOWN_WORDS, WORDS_AT_ONCE = 60_000, 20_000
#: Labels whose counts are sent to all tasks; more than that are joined.
BROADCAST_LABELS = 10_000
ODD = np.uint64(0x9E3779B97F4A7C15)  # an odd multiplier: neighbouring keys get places far apart


def words_of(line: str) -> list[str]:
    """Runs of letters. What the pattern takes for letters besides (superscripts, fractions, Roman numeral signs) divides words."""
    found = WORD.findall(line)
    if line.isascii() or all(map(str.isalpha, found)):
        return found
    return [w for x in found for w in ("".join(c if c.isalpha() else " " for c in x)).split()]


def feature_keys(words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Letter n-grams and affixes of words as numbers: (bigrams, trigrams by place, first place of each word, affixes of three letters (words, 2)).

    A word stands between a beginning and an end mark, so its n-grams there are its affixes of one and two letters. 0 is no feature.
    """
    size = np.fromiter(map(len, words), np.int64, len(words)) + 2
    first = np.cumsum(size) - size
    c = np.frombuffer(("^" + "$^".join(words) + "$").encode("utf-32-le"), np.uint32).astype(np.uint64) if words else np.empty(0, np.uint64)
    left = np.repeat(first + size, size) - np.arange(len(c))  # characters of the word from here on
    one, two = np.append(c[1:], 0).astype(np.uint64), np.append(c[2:], [0, 0]).astype(np.uint64)[: len(c)]
    bi = np.where(left >= 2, (c << np.uint64(21)) | one, np.uint64(0))
    tri = np.where(left >= 3, (((c << np.uint64(21)) | one) << np.uint64(21)) | two, np.uint64(0))
    long = size >= 5
    ends = np.zeros((len(words), 2), np.uint64)
    for k, at in ((0, first + 1), (1, first + size - 4)):
        inner = tri[at[long]]  # a trigram has 63 bits: the highest one marks affixes
        ends[long, k] = inner | np.uint64(1 << 63) if k == 0 else ~inner
    return bi, tri, first, ends


class KeyTable:
    """Numbers of keys by open addressing; `missing` for a key that is not there."""

    def __init__(self, keys: np.ndarray):
        self.missing = len(keys)
        bits = max(4, int(4 * len(keys)).bit_length())
        self.shift = np.uint64(64 - bits)
        self.keys, self.values = np.zeros(1 << bits, np.uint64), np.full(1 << bits, len(keys), np.int32)
        self.probes = 0
        todo = np.arange(len(keys))
        while len(todo):
            at = self._place(keys[todo], self.probes)
            free = np.flatnonzero(self.keys[at] == 0)
            _, pick = np.unique(at[free], return_index=True)
            won = free[pick]
            self.keys[at[won]], self.values[at[won]] = keys[todo[won]], todo[won]
            todo = np.delete(todo, won)
            self.probes += 1

    def _place(self, keys: np.ndarray, step: int) -> np.ndarray:
        return (((keys * ODD) >> self.shift).astype(np.int64) + step) & (len(self.keys) - 1)

    def get(self, keys: np.ndarray) -> np.ndarray:
        at = self._place(keys, 0)
        out = np.where(self.keys[at] == keys, self.values[at], self.missing)
        open_ = np.flatnonzero((self.keys[at] != keys) & (self.keys[at] != 0))
        for step in range(1, self.probes):
            if not len(open_):
                break
            at = self._place(keys[open_], step)
            hit = self.keys[at] == keys[open_]
            out[open_[hit]] = self.values[at[hit]]
            open_ = open_[~hit & (self.keys[at] != 0)]
        return out


def drawn(rows: DataFrame, counts: DataFrame, per_label: dict | int, key: str) -> DataFrame:
    """Of rows (_y, ...), about per_label of each label, with their chance `_p` of being drawn: by a hash of the key column."""
    if isinstance(per_label, dict):
        goal = F.lit(0)
        for y, n in per_label.items():
            goal = F.when(F.col("_y") == y, n).otherwise(goal)
    else:
        goal = F.lit(per_label)
    share = counts.select(F.col("_y").alias("_l"), F.least(F.lit(1.0), goal / F.col("n")).alias("_p"))
    side = F.broadcast(share) if counts.limit(BROADCAST_LABELS + 1).count() <= BROADCAST_LABELS else share
    chance = F.pmod(F.xxhash64(F.lit("sample"), F.col(key)), F.lit(1 << 30)) / float(1 << 30)
    return rows.withColumn("_u", chance).join(side, F.col("_y") == F.col("_l")).where(F.col("_u") < F.col("_p")).drop("_l")


def sampled(docs: DataFrame, may: Column, label: str, per_label: int) -> list:
    """(text, label) of about per_label rows of each label, chosen by a hash of the row; all labels are learned."""
    rows = docs.where(may & F.col(label).isNotNull()).select(F.xxhash64("doc_id", "text").alias("_id"), "text", F.col(label).alias("_y"))
    counts = rows.groupBy("_y").agg(F.count(F.lit(1)).alias("n"))
    got = drawn(rows, counts, per_label, "_id").select("text", "_y").collect()
    return sorted(((r["text"] or "", r["_y"]) for r in got), key=lambda x: (str(x[1]), x[0]))


def labelled(docs: DataFrame, labels: DataFrame, may: Column, label: str, per_label: dict[int, int]) -> list[tuple[str, int, float]]:
    """(text, 0 or 1, weight) of about per_label[y] rows of each label y. The ids are drawn first, so a bounded set of them meets the texts.

    A row's weight is how many rows of its label it stands for, over the mean of that: weighted, the sample has the table's shares of labels.
    """
    known = labels.select("doc_id", F.col(label).cast("int").alias("_y")).where(F.col("_y").isin(0, 1) & F.col("doc_id").isNotNull()).where(may)
    counts = known.groupBy("_y").agg(F.count(F.lit(1)).alias("n"))
    chosen = drawn(known, counts, per_label, "doc_id").select("doc_id", "_y", "_p")
    got = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").select("text", "_y", "_p").collect()
    mean = sum(1 / r["_p"] for r in got) / max(1, len(got))
    return sorted(((r["text"] or "", r["_y"], 1 / r["_p"] / mean) for r in got), key=lambda x: (x[1], x[0]))


class Model:
    """What the fit found; sent to the workers. The weights' last row is that of features which are not known."""

    def __init__(self, langs: list[str], keys: np.ndarray, lexicon: dict[str, int], weights: np.ndarray, transitions: np.ndarray):
        self.langs, self.table, self.lexicon = langs, KeyTable(keys), lexicon
        self.n_keys = len(keys)
        self.weights, self.transitions = np.vstack([weights, np.zeros((1, len(langs)))]).astype(np.float32), transitions.astype(np.float32)
        self.id = uuid.uuid4().hex

    def rows(self, words: list[str]) -> np.ndarray:
        """Scores of words on their own: the bias, their n-grams and affixes, and the lexicon's."""
        out = np.empty((len(words), len(self.langs)), np.float32)
        none = len(self.weights) - 1
        place = lambda keys: np.where((i := self.table.get(keys)) == self.n_keys, none, i)
        for at in range(0, len(words), WORDS_AT_ONCE):
            part = words[at : at + WORDS_AT_ONCE]
            bi, tri, first, ends = feature_keys(part)
            grams = self.weights[place(bi)] + self.weights[place(tri)]
            own = np.fromiter((self.lexicon.get(w, none) for w in part), np.int64, len(part))
            out[at : at + len(part)] = np.add.reduceat(grams, first, axis=0) + self.weights[place(ends.ravel())].reshape(len(part), 2, -1).sum(1) + self.weights[own] + self.weights[none - 1]
        return out

    def scores(self, words: list[str]) -> np.ndarray:
        """Scores (n, languages) of words; those of known words come from this worker's table."""
        known, table = worker_state(self.id, lambda: ({}, [np.zeros((0, len(self.langs)), np.float32)]))
        new = list(set(words).difference(known))
        if len(known) + len(new) > KNOWN_WORDS:
            known.clear()
            table[0] = table[0][:0]
            new = list(set(words))
        if new:
            known.update(zip(new, range(len(known), len(known) + len(new)), strict=True))
            table[0] = np.concatenate([table[0], self.rows(new)])
        return table[0][np.fromiter(map(known.__getitem__, words), np.int64, len(words))]

    def marginals(self, words: list[str], sizes: np.ndarray) -> np.ndarray:
        """Probabilities (words, languages) of the words of lines with these numbers of words, none of them empty."""
        return forward_backward(self.scores(words), Layout(sizes), self.transitions)

    def label(self, lines: list[list[str]]) -> np.ndarray:
        """Marginal probabilities (words, languages) of the words of non-empty lines."""
        return self.marginals(list(chain.from_iterable(lines)), np.array([len(x) for x in lines], np.int64))


def learn(sample: list[tuple[str, str]], train_words: int = 60_000, lexicon: int = 400, min_count: int = 2, steps: int = 25, seed: int = 7) -> Model | None:
    """Fit a model to (text, language) pairs; train_words bounds the words it sees."""
    langs = sorted({y for _, y in sample})
    if not langs:
        return None
    rnd = random.Random(seed)
    lines = [(x, langs.index(y)) for t, y in sample for line in t.split("\n") if (x := words_of(line.lower()))]
    rnd.shuffle(lines)
    by_lang: dict[int, list] = {}
    room = dict.fromkeys(range(len(langs)), train_words // len(langs))
    for x, y in lines:
        if room[y] > 0:
            by_lang.setdefault(y, []).append(x)
            room[y] -= len(x)
    chains: list[tuple[list[str], list[int]]] = []
    pool = [(x, y) for y, xs in by_lang.items() for x in xs]
    if not pool:
        return None
    rnd.shuffle(pool)
    while pool:
        words, ys = [], []
        for _ in range(1 if rnd.random() < 0.5 else 3):  # half of the lines stay as they are, the others are joined by threes
            if pool:
                x, y = pool.pop()
                words += x
                ys += [y] * len(x)
        chains.append((words, ys))
    words = [w for x, _ in chains for w in x]
    y = np.array([v for _, v in chains for v in v], np.int64)
    counts = Counter(words)
    top = {w for k in range(len(langs)) for w, _ in Counter(w for x in by_lang.get(k, []) for w in x).most_common(lexicon)}
    types = {w: i for i, w in enumerate(counts)}
    bi, tri, first, ends = feature_keys(list(types))
    owner = np.repeat(np.arange(len(types)), np.diff(np.append(first, len(bi))))
    key, of = np.concatenate([bi, tri, ends.ravel()]), np.concatenate([owner, owner, np.repeat(np.arange(len(types)), 2)])
    key, of = key[key != 0], of[key != 0]
    known, place, n = np.unique(key, return_inverse=True, return_counts=True)
    number = np.where(n >= min_count, np.cumsum(n >= min_count) - 1, -1)
    keys = known[n >= min_count]
    place = number[place]
    of, place = of[place >= 0], place[place >= 0]
    lexicon_at = {w: len(keys) + i for i, w in enumerate(sorted(top))}
    bias = len(keys) + len(lexicon_at)
    of = np.concatenate([of, [types[w] for w in lexicon_at], np.arange(len(types))]).astype(np.int64)
    place = np.concatenate([place, list(lexicon_at.values()), np.full(len(types), bias)]).astype(np.int64)
    order = np.argsort(of, kind="stable")
    of, place = of[order], place[order]
    starts = np.searchsorted(of, np.arange(len(types)))
    items = Bags(np.array([types[w] for w in words], np.int64), place, starts, bias + 1)
    w, t = fit(items, y, np.array([len(x) for x, _ in chains], np.int64), len(langs), steps=steps)
    return Model(langs, keys, lexicon_at, w, t)


def fitted(docs: DataFrame, may: Column, docs_per_lang: int = 250, train_words: int = 60_000) -> Model | None:
    return learn(sampled(docs, may, "lang", docs_per_lang), train_words)


def text_lines(text: str) -> Iterator[list[str]]:
    for line in text.lower().split("\n"):
        if w := words_of(line):
            yield w


def predict(docs: DataFrame, model: Model | None, carry: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The carried columns, lang_pred, score, and lang_shares array<double> in the alphabetical order of the model's languages."""
    outputs = ("lang_pred", "score", "lang_shares")
    carry = tuple(c for c in carry if c not in outputs)
    types = dict(docs.dtypes)
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(b: pa.RecordBatch) -> pa.RecordBatch:
        m = sent.value
        langs, scores, shares = [], [], []
        of, lines = [], []
        rows = texts(b.column("text"))
        if m is not None:
            for i, t in enumerate(rows):
                own = list(text_lines(t))
                lines += own
                of += [i] * len(own)
        if lines:
            words = list(chain.from_iterable(lines))
            size = np.fromiter(map(len, lines), np.int64, len(lines))
            marg = m.marginals(words, size)
            letters, doc = np.fromiter(map(len, words), np.float64, len(words)), np.repeat(of, size)
            sums = np.stack([np.bincount(doc, marg[:, k] * letters, len(rows)) for k in range(len(m.langs))], 1)
        else:
            sums = np.zeros((len(rows), 1))
        for s, total, k in zip(sums, sums.sum(1), sums.argmax(1), strict=True):
            langs.append(m.langs[k] if total > 0 else "und")
            scores.append(min(1.0, float(s[k] / total)) if total > 0 else 0.0)
            shares.append((s / total).tolist() if total > 0 else [])
        done = [pa.array(langs, pa.string()), pa.array(scores, pa.float64()), pa.array(shares, pa.list_(pa.float64()))]
        return pa.RecordBatch.from_arrays([*(b.column(c) for c in carry), *done], [*carry, *outputs])

    return map_text(docs.select(*dict.fromkeys([*carry, "text"])), run, ", ".join([*(f"`{c}` {types[c]}" for c in carry), "lang_pred string, score double, lang_shares array<double>"]))


def word_labels(text: str, model: Model) -> list[tuple[str, str, float]]:
    """(word, language, probability) for each word of a text."""
    lines = list(text_lines(text))
    if not lines:
        return []
    marg = model.label(lines)
    return [(w, model.langs[p.argmax()], float(p.max())) for w, p in zip((w for x in lines for w in x), marg, strict=True)]
