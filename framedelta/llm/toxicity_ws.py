"""Toxicity by weak supervision: many lexicon and pattern voters, a generative model of their labels, a linear classifier.

Voters: each word of a fixed lexicon; words and beginnings of at least four letters that a bounded sample of labelled rows, weighted to the table's shares of labels, shows to be telling; counts of
such hits; and shapes of a text (no hit at all, shouting, insults put to someone). A voter says toxic, not toxic or nothing.

Label model: the true label is hidden. Each voter has a distribution of its votes for either label; voters which agree more than
their accuracy explains hang together: every voter may have one parent, the one it depends on most given the label (a
forest of greatest conditional mutual information). Expectation-maximisation estimates accuracies, correlations and the
posterior label of each sampled row, labelled or not.

Classifier: a logistic regression on counts of the patterns, fitted to the posterior labels, scores every whole text. Patterns are found by one
Aho-Corasick automaton.

All samples are bounded by parameters (`per_label`, `unlabelled`), and the fit runs on the driver.

Defined cases: null and empty texts get the score of a text without hits. Without labels the lexicon's voters and shapes decide alone.
Repeated rows, null ids and extra columns change nothing. An empty table gives an empty result.
"""

from __future__ import annotations

import re
import uuid
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import map_text, texts, worker_state
from .langid_crf import WORD, labelled
from .quality_crf import logistic

# Common insults.
LEXICON = "idiot moron stupid loser trash scum pathetic worthless disgusting clown dumb fool jerk imbecile garbage filth vermin liar coward creep freak pig ugly hate".split()
YOU = re.compile(r"\b(?:you|your|du|ihr|tu|vous|tú|usted|ustedes)\b")


class Patterns:
    """Word beginnings ("abc*") and whole words ("abc") to count in a text."""

    def __init__(self, names: list[str]):
        self.names, self.id = names, uuid.uuid4().hex

    def automaton(self):
        import ahocorasick

        a = ahocorasick.Automaton()
        for i, n in enumerate(self.names):
            key = n.rstrip("*")
            a.add_word(key, (*(a.get(key) if a.exists(key) else ()), (i, len(key), n.endswith("*"))))
        a.make_automaton()
        return a

    def counts(self, text: str) -> dict[int, int]:
        """How often each pattern begins a word of the text, its case aside; whole words must end there."""
        a = worker_state(self.id, self.automaton)
        found: dict[int, int] = {}
        if not self.names:
            return found
        low = text.lower()
        for end, hits in a.iter(low):
            for i, size, begins in hits:
                at = end - size
                if (at < 0 or not low[at].isalpha()) and (begins or end + 1 == len(low) or not low[end + 1].isalpha()):
                    found[i] = found.get(i, 0) + 1
        return found


def telling(sample: list[tuple[str, int, float]], least: int = 6, precision: float = 0.9, most: int = 400, shortest: int = 4) -> list[str]:
    """Patterns of at least `least` toxic texts, of whose texts the share `precision` is toxic: beginnings of four to eight letters, the shortest that will do first, and words.

    Shares are the table's: rows count by their weights.
    """
    seen: tuple[Counter, Counter] = (Counter(), Counter())
    texts_of: Counter = Counter()
    for t, y, v in sample:
        words = set(WORD.findall(t.lower()))
        found = {w[:k] + "*" for w in words for k in range(shortest, min(8, len(w)) + 1)} | words
        for p in found:
            seen[y][p] += v
        if y:
            texts_of.update(found)
    total = [sum(v for _, y, v in sample if y == k) for k in (0, 1)]
    prior = total[1] / max(1e-9, sum(total))
    odds = {}
    for p, n in texts_of.items():
        if n < least:
            continue
        bad, good = seen[1][p], seen[0][p]
        if bad / (bad + good) >= max(precision, 1 - 0.5 * (1 - prior)):
            odds[p] = n
    # what occurs in just as many texts and says more stands for a beginning
    fuller: dict[str, str] = {}
    for p, n in odds.items():
        less = p[:-2] + "*" if p.endswith("*") else p[:8] + "*"
        while not p.endswith("*") and len(less) > shortest + 1 and odds.get(less) != n:
            less = less[:-2] + "*"
        if odds.get(less) == n and (p.endswith("*") or less not in fuller):
            fuller[less] = p
    out: list[str] = []
    taken: set[str] = set()
    for p in sorted(odds, key=lambda p: (len(p.rstrip("*")), not p.endswith("*"), p)):
        key = p.rstrip("*")
        if not any(key[:k] in taken for k in range(shortest, len(key) + 1)):
            if p.endswith("*"):
                taken.add(key)
            while (longer := fuller.get(p)) is not None:
                p = longer
            out.append(p)
    return sorted(out, key=lambda p: (-odds[p], p))[:most]


def shape(text: str) -> tuple[int, int, bool, bool]:
    """Words, capital words, someone is addressed, exclamations."""
    words = text.split()
    return len(words), sum(w.isupper() and len(w) > 2 for w in words), bool(YOU.search(text.lower())), text.count("!") > 3


def votes_of(text: str, pats: Patterns) -> list[int]:
    """1 toxic, 0 not toxic, -1 no vote, for each voter."""
    found = pats.counts(text)
    n, caps, you, loud = shape(text)
    hits = sum(found.values())
    out = [1 if i in found else -1 for i in range(len(pats.names))]
    out.append(0 if not hits else -1)
    out.append(1 if hits >= 2 else -1)
    out.append(1 if n and hits / n > 0.01 else 0 if n > 50 and hits / n < 0.001 else -1)
    out.append(1 if hits and you else -1)
    out.append(1 if hits and (loud or 2 * caps > n) else -1)
    return out


class LabelModel:
    """P(label) and P(vote | label, parent's vote) for each voter, by expectation-maximisation."""

    def __init__(self, prior: float = 0.1, rounds: int = 25, strength: float = 2.0, dependent: float = 0.02):
        self.prior, self.rounds, self.strength, self.dependent = prior, rounds, strength, dependent
        self.parent: list[int] = []
        self.table: list[np.ndarray] = []

    def _structure(self, onehot: np.ndarray, q: np.ndarray, weight: np.ndarray) -> list[int]:
        """A forest of the greatest conditional mutual information between voters given the label."""
        n, m, v = onehot.shape
        info = np.zeros((m, m))
        flat = onehot.reshape(n, m * v)
        for y in (0, 1):
            w = weight * (q if y else 1 - q)
            total = w.sum() + 1e-9
            joint = ((flat * w[:, None]).T @ flat).reshape(m, v, m, v).transpose(0, 2, 1, 3) / total
            own = (onehot * w[:, None, None]).sum(0) / total
            with np.errstate(divide="ignore", invalid="ignore"):
                term = joint * np.log(joint / (own[:, None, :, None] * own[None, :, None, :]))
            info += total / n * np.nansum(np.where(joint > 0, term, 0), (2, 3))
        parent, joined = [-1] * m, list(range(m))

        def root(i):
            while joined[i] != i:
                i = joined[i]
            return i

        near: dict[int, list[int]] = {}
        i, j = np.triu_indices(m, 1)
        for k in np.argsort(-info[i, j], kind="stable"):
            if info[i[k], j[k]] < self.dependent:
                break
            a, b = root(i[k]), root(j[k])
            if a != b:
                joined[b] = a
                near.setdefault(int(i[k]), []).append(int(j[k]))
                near.setdefault(int(j[k]), []).append(int(i[k]))
        done: set[int] = set()
        for r in range(m):
            todo = [r] if r not in done else []
            done.update(todo)
            while todo:
                x = todo.pop()
                for z in near.get(x, []):
                    if z not in done:
                        done.add(z)
                        parent[z] = x
                        todo.append(z)
        return parent

    def _maximise(self, onehot: np.ndarray, q: np.ndarray, base: np.ndarray, weight: np.ndarray) -> None:
        self.table = []
        for j, p in enumerate(self.parent):
            t = np.zeros((2, 3, 3))
            for y, w in ((0, weight * (1 - q)), (1, weight * q)):
                t[y] = (onehot[:, p].T * w) @ onehot[:, j] if p >= 0 else np.tile((w[:, None] * onehot[:, j]).sum(0), (3, 1))
            t += self.strength * base[j][:, None, :]
            self.table.append(t / t.sum(2, keepdims=True))

    def posterior(self, votes: np.ndarray) -> np.ndarray:
        z = np.tile(np.log([1 - self.prior, self.prior]), (len(votes), 1))
        for j, p in enumerate(self.parent):
            before = votes[:, p] + 1 if p >= 0 else np.zeros(len(votes), np.int64)
            z += np.log(self.table[j][:, before, votes[:, j] + 1]).T
        z -= z.max(1, keepdims=True)
        e = np.exp(z)
        return e[:, 1] / e.sum(1)

    def fit(self, votes: np.ndarray, known: np.ndarray, weight: np.ndarray | None = None) -> np.ndarray:
        """Posterior of each row; `known` is a first guess: 0 or 1, or -1 where a majority of votes is the guess. `weight` has a mean of about 1."""
        weight = np.ones(len(votes)) if weight is None else weight
        onehot = (votes[:, :, None] == np.array([-1, 0, 1])).astype(float)
        for_, against = (votes == 1).sum(1), (votes == 0).sum(1)
        guess = np.where(for_ > against, 0.9, np.where(for_ < against, 0.02, self.prior))
        q = np.where(known == 1, 0.95, np.where(known == 0, 0.02, guess))
        base = np.tile(np.array([[0.6, 0.3, 0.1], [0.6, 0.1, 0.3]]), (votes.shape[1], 1, 1))  # before any data a vote is right more often than not
        self.parent = [-1] * votes.shape[1]
        for r in range(self.rounds):
            if r % max(1, self.rounds // 3) == 0:  # from the start, or voters who copy each other would pass for the label
                self.parent = self._structure(onehot, q, weight)
            self._maximise(onehot, q, base, weight)
            q = self.posterior(votes)
            self.prior = float(np.clip((weight * q).sum() / weight.sum(), 0.001, 0.5))
        return q


def measures(text: str, pats: Patterns) -> np.ndarray:
    """What the linear classifier sees."""
    found = pats.counts(text)
    n, caps, you, loud = shape(text)
    hits = sum(found.values())
    x = np.zeros(len(pats.names) + 7)
    for i, k in found.items():
        x[i] = np.log1p(k)
    x[len(pats.names) :] = [np.log1p(hits), hits >= 2, len(found) >= 2, np.log1p(1000 * hits / max(n, 1)), bool(hits) and you, caps / max(n, 1), loud]
    return x


class Model:
    def __init__(self, pats: Patterns, weights: np.ndarray):
        self.pats, self.weights = pats, weights

    def score(self, rows: list[str]) -> np.ndarray:
        z = np.array([measures(t, self.pats) @ self.weights[:-1] for t in rows]) + self.weights[-1] if rows else np.zeros(0)
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def learn(sample: list[tuple[str, int, float]], unlabelled: list[str], voters: int = 150) -> Model:
    """Fit to labelled (text, 0 or 1, weight) and texts without labels, which weigh 1."""
    names = list(dict.fromkeys([*telling(sample)[:voters], *LEXICON]))
    pats = Patterns(names)
    rows = [t for t, *_ in sample] + unlabelled
    weight = np.array([v for *_, v in sample] + [1.0] * len(unlabelled))
    if not rows:
        rows, weight = ["", " ".join(LEXICON)], np.ones(2)
    known = np.array([y for _, y, _ in sample] + [-1] * (len(rows) - len(sample)))
    votes = np.array([votes_of(t, pats) for t in rows])
    model = LabelModel(prior=0.1)
    q = model.fit(votes, known, weight)
    return Model(pats, logistic(np.array([measures(t, pats) for t in rows]), q, l2=2e-3, weight=weight))


def fitted(docs: DataFrame, labels: DataFrame, may: Column, label: str = "toxic", per_label: int = 1000, unlabelled: int = 1000) -> Model:
    """Learn from about per_label toxic texts and three times as many others that `may` allows, and `unlabelled` other texts, drawn by a hash."""
    n = docs.count()
    chance = F.pmod(F.xxhash64(F.lit("more"), F.col("doc_id"), F.col("text")), F.lit(1 << 30)) / float(1 << 30)
    more = docs.select("text").where(may & (chance < unlabelled / max(1, n))).collect()
    return learn(labelled(docs, labels, may, label, {0: 3 * per_label, 1: per_label}), sorted(r["text"] or "" for r in more))


def predict(docs: DataFrame, model: Model, threshold: float = 0.5, carry: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The carried columns, score double and predicted int."""
    carry = tuple(c for c in carry if c not in ("score", "predicted"))
    types = dict(docs.dtypes)
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(b: pa.RecordBatch) -> pa.RecordBatch:
        s = sent.value.score(texts(b.column("text")))
        done = [pa.array(s, pa.float64()), pa.array((s >= threshold).astype(np.int32), pa.int32())]
        return pa.RecordBatch.from_arrays([*(b.column(c) for c in carry), *done], [*carry, "score", "predicted"])

    return map_text(docs.select(*dict.fromkeys([*carry, "text"])), run, ", ".join([*(f"`{c}` {types[c]}" for c in carry), "score double, predicted int"]))
