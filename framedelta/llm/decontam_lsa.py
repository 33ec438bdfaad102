"""Benchmark decontamination by latent semantic retrieval: which documents hold a benchmark passage, word for word or reworded.

Terms are the words of the benchmark's passages, weighted by their inverse document frequency over all documents. All documents and the benchmark's
passages are the rows of a sparse TF-IDF matrix whose right singular vectors come from a
distributed randomised SVD: each partition adds up its part of A'(A Q) and only those small products meet. What a document has of the terms is counted
once and written, so texts are not read again for that. A benchmark
passage is a query in the latent space. Every document is cut into overlapping windows at several scales; a window is compared with
the passages of about its length. The share of a window's weight that lies in benchmark terms bounds its cosine, so windows
below the threshold in that are not projected at all, which changes nothing.

The latent cosine loses copies: of passages which the kept directions do not hold, of passages frequent enough for their weights to
fall below those of the words around them, and of lengths far from every scale. So a second path, without weights or windows, finds every place where
a leak can be: a subsequence of `lcs` of the passage's words leaves out so few that some of any larger set of its words must be
there, and the rarest such set (its seeds) is looked up. It depends on neither the rank nor the block size. As nothing else can be a leak, only
windows near enough seeds are projected.

Candidates are checked word by word: the longest common subsequence of passage and the text around the window, and the
passage's rarest words, which stand for its answer. A pair is a leak if the subsequence covers `lcs` of the passage, or
`reworded` of it while `answers` of the rarest words are there. All leaks are found that lie within the larger of one and a
half lengths of the passage and a window of its scale with half a passage on both sides.

The benchmark is a stated query set, taken in blocks of `block_items`; what is broadcast is bounded by a block. Nothing of the documents is
sampled, neither in the search nor for the directions: all documents together weigh as `background_passages` passages there, or the benchmark's own
directions would be lost among those of a large corpus.

Defined cases: null and empty texts hold nothing. Passages of fewer than `min_words` words leak where all their words follow each other
in the text; null ones and those without words are not searched for. Repeated
rows are reported each, with their doc_id, null included. An empty table or benchmark gives an empty result.
"""

from __future__ import annotations

import re
from collections import Counter
from itertools import chain, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import delete, map_batches, map_text, new_path, texts

TERM = re.compile(r"\w+")
SCALES = (14, 22, 34, 52, 80, 120)


#: For texts in Latin-1: each character lower-cased, or a space where it is no part of a word.
LATIN = bytes(ord(chr(i).lower()) if TERM.match(chr(i)) else 32 for i in range(256))


def terms(text: str | None) -> list[str]:
    """The lower-cased words of a text. Latin-1 is translated as a whole, which is several times faster than a search for words."""
    try:
        return (text or "").encode("latin-1").translate(LATIN).decode("latin-1").split()
    except UnicodeEncodeError:
        return TERM.findall(text.lower())


def holds(words: list[str], run: list[str]) -> bool:
    """Whether the words of `run` follow each other in words."""
    return f" {' '.join(run)} " in f" {' '.join(words)} "


COUNTS = "terms array<int>, counts array<int>, n_words int"
OUTPUTS = ("doc_id", "item_id", "cosine", "lcs_share", "answer_share", "first_word")


def counted(rows: list[list[str]], vocab: dict[str, int]) -> pa.RecordBatch:
    """(terms, counts, n_words) of each text's words: which terms it holds, how often, and all of its words."""
    size = np.array([len(w) for w in rows], np.int64)
    ids = np.fromiter(map(vocab.get, chain.from_iterable(rows), repeat(-1)), np.int64, int(size.sum()))
    key, n = np.unique((np.repeat(np.arange(len(rows)), size) * len(vocab) + ids)[ids >= 0], return_counts=True)
    row, term = np.divmod(key, len(vocab))
    ends = pa.array(np.searchsorted(row, np.arange(len(rows) + 1)).astype(np.int32))
    lists = [pa.ListArray.from_arrays(ends, pa.array(x.astype(np.int32))) for x in (term, n)]
    return pa.RecordBatch.from_arrays([*lists, pa.array(size.astype(np.int32))], ["terms", "counts", "n_words"])


def term_counts(passages: DataFrame, vocab: dict[str, int]) -> DataFrame:
    """What counted() gives for each text."""
    sent = passages.sparkSession.sparkContext.broadcast(vocab)
    return map_text(passages.select("text"), lambda b: counted([terms(t) for t in texts(b.column("text"))], sent.value), COUNTS)


def document_frequency(counts: DataFrame, size: int) -> np.ndarray:
    """In how many rows of term_counts each of `size` terms occurs, over all of them."""

    def run(batches):
        n = np.zeros(size, np.int64)
        for b in batches:
            n += np.bincount(b.column("terms").flatten().to_numpy(zero_copy_only=False), minlength=size)
        held = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(held.astype(np.int32)), pa.array(n[held])], ["term", "n"])

    out = np.zeros(size)
    for r in map_batches(counts.select("terms"), run, "term int, n bigint").groupBy("term").agg(F.sum("n").alias("n")).collect():
        out[r["term"]] = r["n"]
    return out


def singular_vectors(passages: DataFrame, vocab: dict[str, int], idf: np.ndarray, other: float, rank: int, over: int = 16, power: int = 2, seed: int = 11) -> np.ndarray:
    """About `rank` right singular vectors (terms, rank) of the TF-IDF matrix of all passages: texts, or term_counts with the `weight` of each row."""
    spark = passages.sparkSession
    rows = passages if "terms" in passages.columns else term_counts(passages, vocab).withColumn("weight", F.lit(1.0))
    size = len(vocab)
    rank = min(rank, size)
    q = np.linalg.qr(np.random.default_rng(seed).normal(size=(size, min(size, rank + over))))[0]
    block = 1024
    weight = spark.sparkContext.broadcast(idf)
    step = max(1, min(1024, (64 << 20) // (4 * size)))  # rows that a task multiplies at once
    for _ in range(power + 1):
        sent = spark.sparkContext.broadcast(q.astype(np.float32))

        def part(batches):
            basis, w = sent.value, weight.value  # noqa: B023
            total = np.zeros(basis.shape)
            dense = np.zeros((step, size), np.float32)
            for whole in batches:
                for at in range(0, whole.num_rows, step):
                    b = whole.slice(at, step)
                    n = b.column("terms").value_lengths().to_numpy(zero_copy_only=False)
                    idx, count = (b.column(c).flatten().to_numpy(zero_copy_only=False) for c in ("terms", "counts"))
                    row = np.repeat(np.arange(len(n)), n)
                    x = count * w[idx]
                    others = b.column("n_words").to_numpy(zero_copy_only=False) - np.bincount(row, count, len(n))
                    norm = np.sqrt(np.bincount(row, x * x, len(n)) + others * other**2)
                    dense[row, idx] = x * (b.column("weight").to_numpy() / np.maximum(norm, 1e-12))[row]
                    a = dense[: len(n)]
                    total += a.T @ (a @ basis)
                    dense[row, idx] = 0
            parts = [total[i : i + block].tobytes() for i in range(0, len(total), block)] if total.any() else []
            yield pa.RecordBatch.from_arrays([pa.array(range(len(parts)), pa.int32()), pa.array(parts, pa.binary())], ["block", "sums"])

        def add(batches):
            sums: dict[int, np.ndarray] = {}
            for b in batches:
                for i, x in zip(b.column("block").to_pylist(), b.column("sums").to_pylist(), strict=True):
                    x = np.frombuffer(x)
                    sums[i] = sums[i] + x if i in sums else x
            yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array([x.tobytes() for x in sums.values()], pa.binary())], ["block", "sums"])

        # sums are as large for few rows as for many, so there are no more of them than tasks at once
        parts = map_batches(rows.coalesce(spark.sparkContext.defaultParallelism), part, "block int, sums binary")
        z = np.zeros(q.shape)
        for r in map_batches(parts.repartition(F.col("block")), add, "block int, sums binary").collect():
            x = np.frombuffer(bytes(r["sums"])).reshape(-1, q.shape[1])
            z[r["block"] * block : r["block"] * block + len(x)] += x
        u, s, _ = np.linalg.svd(z, full_matrices=False)
        q = u
    return q[:, :rank][:, s[:rank] > 1e-9 * max(s[0], 1e-30)]


class Queries:
    """A block of benchmark passages in the latent space, with what their checks need."""

    def __init__(self, items: list[tuple], vocab: dict[str, int], idf: np.ndarray, vectors: np.ndarray, other: float, lcs: float = 0.7, answers: float = 0.75):
        self.ids = [i for i, _ in items]
        self.words = [w for _, w in items]
        self.vocab, self.idf, self.other = vocab, idf, other
        self.vectors = (idf[:, None] * vectors).astype(np.float32)  # a term's weighted place in the latent space
        self.scale = np.array([int(np.argmin([abs(np.log(len(w) / s)) for s in SCALES])) for w in self.words])
        self.latent, self.masks, self.rare = [], [], []
        for w in self.words:
            idx = np.array([vocab[x] for x in w])
            norm = np.sqrt((idf[idx] ** 2).sum()) + 1e-12
            self.latent.append(self.vectors[idx].sum(0) / norm)
            mask: dict[str, int] = {}
            for k, x in enumerate(w):
                mask[x] = mask.get(x, 0) | 1 << k
            self.masks.append(mask)
            best = sorted(set(w), key=lambda x: (-idf[vocab[x]], x))
            self.rare.append(frozenset(best[: max(3, len(best) // 4)]))
        self.latent = np.array(self.latent, np.float32)
        self._index_seeds(lcs, answers)

    def _index_seeds(self, lcs: float, answers: float) -> None:
        """For each term, the items it is a seed of. A leak holds `need` seeds of its item, or `need_rare` of its rarest words."""
        length = np.array([len(w) for w in self.words], np.int64)
        self.hop = length // 2 + (length < 2)
        self.span = np.maximum(length + self.hop, np.array(SCALES)[self.scale] + 2 * (length // 2))  # the longest place of a leak, no shorter than a window with its surroundings
        self.region = self.span + self.hop  # a region starts at every hop, so one of them holds the place
        self.need, self.need_rare, posts = [], [], []
        for item, w in enumerate(self.words):
            m = len(w)
            least = next((k for k in range(1, m) if k / m >= lcs), m)
            need = min(least, max(2, -(-m // 10)))
            count, left = Counter(w), m - least + need
            for x in sorted(count, key=lambda x: (-self.idf[self.vocab[x]], x)):
                if left > 0 or x in self.rare[item]:
                    posts.append((self.vocab[x], item, x in self.rare[item]))
                left -= count[x]
            rare = len(self.rare[item])
            self.need.append(need)
            self.need_rare.append(next((k for k in range(1, rare) if k / rare >= answers), rare))
        self.need, self.need_rare = np.array(self.need, np.int64), np.array(self.need_rare, np.int64)
        term, self.seed_item, self.seed_rare = (np.array(x, np.int64) for x in zip(*sorted(posts), strict=True))
        self.seed_count = np.bincount(term, minlength=len(self.vocab))
        self.seed_first = np.cumsum(self.seed_count) - self.seed_count

    def common(self, item: int, words: list[str]) -> int:
        """Length of the longest common subsequence, by bit vectors."""
        mask, n = self.masks[item], len(self.words[item])
        full = (1 << n) - 1
        v = full
        for w in words:
            m = mask.get(w)
            if m:
                u = v & m
                v = ((v + u) | (v - u)) & full
        return n - v.bit_count()

    def numbered(self, rows: list[list[str]]) -> tuple[np.ndarray, np.ndarray]:
        """The number of each row's words, and all words' term numbers (-1: none)."""
        size = np.array([len(w) for w in rows], np.int64)
        return size, np.fromiter(map(self.vocab.get, chain.from_iterable(rows), repeat(-1)), np.int64, int(size.sum()))

    def seeded(self, size: np.ndarray, ids: np.ndarray) -> np.ndarray:
        """Rows, items, first words and ends of every region with enough seeds of an item for a leak."""
        first = np.cumsum(size) - size
        row_of = np.repeat(np.arange(len(size)), size)
        at = np.flatnonzero(ids >= 0)
        at = at[self.seed_count[ids[at]] > 0]
        n = self.seed_count[ids[at]]
        post = np.arange(n.sum()) + np.repeat(self.seed_first[ids[at]] - (np.cumsum(n) - n), n)
        item, rare, at = self.seed_item[post], self.seed_rare[post] > 0, np.repeat(at, n)
        order = np.argsort(item, kind="stable")
        item, rare, at = item[order], rare[order], at[order]
        keys = []
        for some, need in ((slice(None), self.need), (rare, self.need_rare)):
            i, a = item[some], at[some]
            last = np.arange(len(i)) + need[i] - 1
            k = np.flatnonzero(last < len(i))
            j = last[k]
            k, j = (x[(i[k] == i[j]) & (row_of[a[k]] == row_of[a[j]]) & (a[j] - a[k] < self.span[i[k]])] for x in (k, j))
            who, row = i[k], row_of[a[k]]
            lo, hi = a[k] - first[row], a[j] - first[row]
            cell = lo // self.hop[who]
            while len(who):
                keys.append((row * len(self.words) + who << 32) + cell)
                cell = cell - 1
                good = (cell >= 0) & (cell * self.hop[who] + self.region[who] > hi)
                who, row, cell, hi = who[good], row[good], cell[good], hi[good]
        if not keys:
            return np.empty((4, 0), np.int64)
        key = np.unique(np.concatenate(keys))
        row, who = np.divmod(key >> 32, len(self.words))
        lo = (key & 0xFFFFFFFF) * self.hop[who]
        return np.stack([row, who, lo, np.minimum(lo + self.region[who], size[row])])

    def cosine(self, item: int, words: list[str]) -> float:
        """The latent cosine of an item and a run of words."""
        ids = np.array([self.vocab.get(w, -1) for w in words], np.int64)
        own = ids[ids >= 0]
        norm = np.sqrt((self.idf[own] ** 2).sum() + (len(ids) - len(own)) * self.other**2) + 1e-12
        return float(self.vectors[own].sum(0) @ self.latent[item] / norm)

    def candidates(self, size: np.ndarray, ids: np.ndarray, seeded: np.ndarray, cosine: float) -> list[tuple[int, int, int, int, float]]:
        """(row, item, first word, end, cosine) of windows near an item, which meet a seeded region of their scale."""
        held = np.unique(seeded[0])  # rows without a region have no window to look at
        first = np.cumsum(size) - size
        ids = ids[np.repeat(first[held] - (np.cumsum(size[held]) - size[held]), size[held]) + np.arange(size[held].sum())]
        size, seeded = size[held], np.stack([np.searchsorted(held, seeded[0]), *seeded[1:]])
        first = np.cumsum(size) - size
        inner = np.where(ids >= 0, self.idf[ids] ** 2, 0.0)
        whole = np.where(ids >= 0, inner, self.other**2)
        c_in, c_all = (np.append(0.0, np.cumsum(x)) for x in (inner, whole))
        out = []
        for s, width in enumerate(SCALES):
            mine = np.flatnonzero(self.scale == s)
            regions = seeded[:, self.scale[seeded[1]] == s]
            if not regions.shape[1]:
                continue
            edges = np.zeros(len(ids) + 1, np.int64)
            np.add.at(edges, first[regions[0]] + regions[2], 1)
            np.add.at(edges, first[regions[0]] + regions[3], -1)
            covered = np.append(0, np.cumsum(np.cumsum(edges[:-1]) > 0))
            step = max(1, width // 4)
            n = np.where(size > width, -(-(size - width) // step) + 1, (size > 0).astype(np.int64))
            row = np.repeat(np.arange(len(size)), n)
            at = (np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)) * step
            end = np.minimum(at + width, size[row])
            a, e = first[row] + at, first[row] + end
            norm = np.sqrt(c_all[e] - c_all[a]) + 1e-12
            live = np.flatnonzero((covered[e] > covered[a]) & (np.sqrt(np.maximum(c_in[e] - c_in[a], 0)) >= cosine * norm))
            for part in np.array_split(live, len(live) // 2000 + 1):
                if not len(part):
                    continue
                spans = e[part] - a[part]
                cuts = np.cumsum(spans) - spans
                pos = np.arange(spans.sum()) - np.repeat(cuts, spans) + np.repeat(a[part], spans)
                hit = ids[pos]
                owner = np.repeat(np.arange(len(part)), spans)[hit >= 0]
                vec = self.vectors[hit[hit >= 0]]
                begin = np.flatnonzero(np.diff(owner, prepend=-1))
                sums = np.add.reduceat(vec, begin, axis=0)
                which = part[owner[begin]]
                near = sums @ self.latent[mine].T / norm[which][:, None]
                for i, j in zip(*np.nonzero(near >= cosine), strict=True):
                    w = which[i]
                    out.append((int(held[row[w]]), int(mine[j]), int(at[w]), int(end[w]), float(near[i, j])))
        return out


def leaks(docs: DataFrame, benchmark: DataFrame, cosine: float = 0.5, lcs: float = 0.7, reworded: float = 0.5, answers: float = 0.75, rank: int = 256, background_passages: int = 1500, min_words: int = 5, block_items: int = 2000) -> DataFrame:
    """(doc_id, item_id, cosine, lcs_share, answer_share double, first_word int) of each row of docs and passage found in it."""
    spark = docs.sparkSession
    kinds = dict(docs.dtypes)["doc_id"], dict(benchmark.dtypes)["item_id"]
    types = (*kinds, "double", "double", "double", "int")
    schema = ", ".join(map(" ".join, zip(OUTPUTS, types, strict=True)))
    rows = benchmark.select("item_id", "text").where("text is not null").collect()
    items = sorted(((r["item_id"], w) for r in rows if (w := terms(r["text"]))), key=str)
    out = spark.range(0).select(*(F.lit(None).cast(kind).alias(name) for name, kind in zip(OUTPUTS, types, strict=True)))
    for at in range(0, len(items), block_items):
        block = items[at : at + block_items]
        vocab = {w: i for i, w in enumerate(dict.fromkeys(x for _, ws in block for x in ws))}
        path = new_path(spark, "term-counts")
        term_counts(docs, vocab).write.parquet(path)
        counts = spark.read.schema(COUNTS).parquet(path)
        total, df = counts.count(), document_frequency(counts, len(vocab))
        idf = np.log((total + 1.0) / (df + 1.0)) + 0.05
        # counted here and sent as Arrow: rows made in Python, and their counting, would be two more Python processes in each task of the SVD
        own = spark.createDataFrame(pa.Table.from_batches([counted([w for _, w in block], vocab)])).withColumn("weight", F.lit(1.0))
        passages = counts.withColumn("weight", F.lit(min(1.0, background_passages / max(1, total)) ** 0.5)).unionAll(own)
        other = float(np.quantile(idf, 0.8))  # what a word outside the benchmark weighs
        v = singular_vectors(passages, vocab, idf, other, rank)
        delete(spark, path)
        sent = spark.sparkContext.broadcast(Queries(block, vocab, idf, v, other, lcs, answers))

        def search(b: pa.RecordBatch) -> pa.RecordBatch:
            q: Queries = sent.value  # noqa: B023
            words = [terms(t) for t in texts(b.column("text"))]
            best: dict[tuple[int, int], tuple] = {}

            def check(row: int, item: int, lo: int, hi: int, cos: float | None) -> None:
                m = len(q.words[item])
                region = words[row][lo:hi]
                share = q.common(item, region) / m if m >= min_words else float(holds(region, q.words[item]))
                if share < min(lcs, reworded):
                    return
                found = len(q.rare[item].intersection(region)) / len(q.rare[item])
                if share >= lcs or (share >= reworded and found >= answers):
                    got = (share, q.cosine(item, region) if cos is None else cos, found, -lo)
                    if got > best.get((row, item), (-1.0,)):
                        best[row, item] = got

            size, ids = q.numbered(words)
            seeded = q.seeded(size, ids)
            for row, item, s, e, cos in q.candidates(size, ids, seeded, cosine):
                half = len(q.words[item]) // 2
                check(row, item, max(0, s - half), e + half, cos)
            known = set(best)
            for row, item, lo, hi in seeded.T.tolist():
                if (row, item) not in known:
                    check(row, item, lo, hi, None)
            keys = sorted(best)
            doc_ids = b.column("doc_id").take(pa.array([r for r, _ in keys], pa.int64()))
            cols = [pa.array([best[k][j] for k in keys], pa.float64()) for j in (1, 0, 2)]
            item_ids = pa.array([q.ids[i] for _, i in keys], pa.Table.from_batches([b]).schema.field("_item").type)
            return pa.RecordBatch.from_arrays([doc_ids, item_ids, *cols, pa.array([-best[k][3] for k in keys], pa.int32())], list(OUTPUTS))

        out = out.unionAll(map_text(docs.select("doc_id", "text", F.lit(None).cast(kinds[1]).alias("_item")), search, schema))
    return out
