"""SimHash near-duplicates of whole texts, verified: texts whose five-word shingles have a Jaccard similarity of at least `least`.

At a similarity of 0.8 two 64-bit fingerprints differ in about ten bits, too many for shards by equal bits (see the README). So shards
are made by min-hash bands of the shingles (a pair at 0.8 misses all twelve bands of four in 2 of 1,000 cases); within a shard the BK-tree
of its fingerprints gives links within a wide radius; and each link is verified on both texts' shingle sets before it counts.

Texts: words are runs of bytes other than ASCII white space, A-Z lowered; shingles are `width` words, for fewer words the whole sequence. Texts
of the same words are one text (by 128 bits of hash) from the start, so copies are never paired.

Shards of more than `hot` texts are taken apart by leaders: in each round those within the radius of one of the shard's leaders are linked to them and
leave the shard, until it is small; so a large group is a few stars, whose links are dealt to many tasks.

These links are the quick part: each text has its nearest and its leaders alone. So when they have been verified, a second pass takes the whole shards again,
hot ones in tiles of several tasks, and verifies every pair within the radius whose texts are not in one class yet. No pair of a shard within the radius is left out.

Defined cases: null and empty texts are one class. Of a class the row with the smallest doc_id stays (null after all others; of equal ids the
least text hash; of repeated rows one). All columns come back. An empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import map_batches, map_text, raw_texts, written
from .simhash import SEED, BKTree, components

BANDS, ROWS = 12, 4
#: Texts to which the others of a hot shard are linked in a round.
LEADERS = 3
#: Links of one text that a task may verify; more are dealt to several tasks.
STAR = 512
#: Tables of leaders and of hot texts are broadcast up to this number of rows.
BROADCAST_ROWS = 100_000
_R = np.random.default_rng(20240229)
ODDS = (_R.integers(0, 1 << 63, BANDS * ROWS, dtype=np.int64).astype(np.uint64) << np.uint64(1)) | np.uint64(1)
MASKS = _R.integers(0, 1 << 63, BANDS * ROWS, dtype=np.int64).astype(np.uint64)


def words(text: bytes) -> list[bytes]:
    return text.lower().split()


def shingle_hashes(w: list[bytes], width: int = 5) -> np.ndarray:
    """64-bit hashes of the shingles, repeats included."""
    if not w:
        return np.empty(0, np.uint64)
    if len(w) < width:
        parts = [b" ".join(w)]
    else:
        parts = list(map(b" ".join, zip(*(w[i:] for i in range(width)), strict=False)))
    digest = xxhash.xxh64_digest
    return np.frombuffer(b"".join([digest(p, SEED) for p in parts]), ">u8").astype(np.uint64)


def sketch(h: np.ndarray) -> tuple[int, list[int]]:
    """(SimHash of all shingles, a key of each min-hash band) as signed numbers."""
    if not len(h):
        return 0, []
    least = np.full(BANDS * ROWS, np.iinfo(np.uint64).max, np.uint64)
    bits = np.zeros(64, np.int64)
    for at in range(0, len(h), 1 << 13):
        part = h[at : at + (1 << 13)]
        np.minimum(least, ((part[:, None] ^ MASKS) * ODDS).min(0), out=least)
        bits += np.unpackbits(part.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int64)
    fp = int.from_bytes(np.packbits(2 * bits > len(h)).tobytes(), "big", signed=True)
    rows = least.reshape(BANDS, ROWS)
    keys = [int.from_bytes(xxhash.xxh64_digest(rows[i].tobytes(), i), "big", signed=True) for i in range(BANDS)]
    return fp, keys


def text_id(w: list[bytes]) -> bytes:
    return xxhash.xxh3_128_digest(b" ".join(w))


def sketches(docs: DataFrame, width: int) -> DataFrame:
    """(doc_id, tid binary, fp bigint, bands array<bigint>) of each row."""
    kind = dict(docs.dtypes)["doc_id"]

    def run(b: pa.RecordBatch) -> pa.RecordBatch:
        tid, fp, bands = [], [], []
        for t in raw_texts(b.column("text")):
            w = words(t)
            f, k = sketch(shingle_hashes(w, width))
            tid.append(text_id(w)), fp.append(f), bands.append(k)
        return pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(tid, pa.binary()), pa.array(fp, pa.int64()), pa.array(bands, pa.list_(pa.int64()))], ["doc_id", "tid", "fp", "bands"])

    return map_text(docs.select("doc_id", "text"), run, f"doc_id {kind}, tid binary, fp bigint, bands array<bigint>")


def with_tid(docs: DataFrame) -> DataFrame:
    """docs with `tid`."""
    types = dict(docs.dtypes)

    def run(b: pa.RecordBatch) -> pa.RecordBatch:
        tid = [text_id(words(t)) for t in raw_texts(b.column("text"))]
        return pa.RecordBatch.from_arrays([*b.columns, pa.array(tid, pa.binary())], [*b.schema.names, "tid"])

    return map_text(docs, run, ", ".join([*(f"`{c}` {types[c]}" for c in docs.columns), "tid binary"]))


def _small(df: DataFrame) -> DataFrame:
    return F.broadcast(df) if df.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS else df


def nearest_links(codes: list[int], radius: int) -> list[tuple[int, int]]:
    """(member, other) of a shard: for each member the members within the radius that are nearest to it, on both sides of it in the shard's order."""
    tree, out = BKTree(codes), []
    for i, c in enumerate(codes):
        best = {False: (radius + 1, -1), True: (radius + 1, -1)}
        far = 0
        for j in tree.near(c, radius):
            if j != i:
                d = (c ^ codes[j]).bit_count()
                best[j > i] = min(best[j > i], (d, j))
                far += 1
        out += [(i, j) for d, j in best.values() if j >= 0]
        if i and far and (c ^ codes[0]).bit_count() <= radius:
            out.append((i, 0))
    return out


def band_keys(texts: DataFrame) -> DataFrame:
    """(tid, fp, k) of each text's bands."""
    return written(texts.select("tid", "fp", F.explode(F.array_distinct("bands")).alias("k")), "band-keys")


def candidates(keys: DataFrame, radius: int, hot: int) -> DataFrame:
    """(a binary, b binary): links, in the BK-trees of the shards, between texts (band keys) within radius bits; distinct."""
    sizes = written(keys.groupBy("k").agg(F.count(F.lit(1)).alias("c")).where("c > 1"), "band-sizes")
    cold = keys.join(sizes.where(F.col("c") <= hot).select("k"), "k")
    rest = keys.join(_small(sizes.where(F.col("c") > hot).select("k")), "k") if sizes.where(F.col("c") > hot).limit(1).count() else None
    stars = []
    turn = 0
    while rest is not None:
        rest = written(rest, "hot-shards")
        first = lambda i: F.min(F.struct(F.xxhash64(F.lit(turn * LEADERS + i), F.col("tid")).alias("p"), F.col("tid").alias("lead"), F.col("fp").alias("lead_fp")))  # noqa: B023, E731
        lead = rest.groupBy("k").agg(F.array(*[first(i) for i in range(LEADERS)]).alias("m"))
        x = rest.join(_small(written(lead, "leaders")), "k")
        close = F.filter("m", lambda m: F.bit_count(F.col("fp").bitwiseXOR(m["lead_fp"])) <= radius)
        x = written(x.select("k", "tid", "fp", F.transform(close, lambda m: m["lead"]).alias("leads"), (F.size(close) > 0).alias("near")), "led")
        stars.append(x.where("near").select(F.explode(F.array_distinct("leads")).alias("a"), F.col("tid").alias("b")).where("a <> b"))
        left = x.where("not near").select("k", "tid", "fp")
        sizes = written(left.groupBy("k").agg(F.count(F.lit(1)).alias("c")).where("c > 1"), "band-sizes")
        cold = cold.unionByName(left.join(sizes.where(F.col("c") <= hot).select("k"), "k").select(*cold.columns))
        rest = left.join(sizes.where(F.col("c") > hot).select("k"), "k").select("k", "tid", "fp") if sizes.where(F.col("c") > hot).limit(1).count() else None
        turn += 1
    dealt = cold.select("k", "fp", "tid").repartition("k").sortWithinPartitions("k", "fp", "tid")

    def links(fp, tid, cuts):
        a, b = [], []
        codes = fp.view(np.uint64).tolist()
        for s, e in zip([0, *cuts], [*cuts, len(fp)], strict=True):
            if e - s > 1:
                for i, j in nearest_links(codes[s:e], radius):
                    a.append(tid[s + j]), b.append(tid[s + i])
        if a:
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.binary()), pa.array(b, pa.binary())], ["a", "b"])

    def walk(batches):
        held = None
        for x in batches:
            t = pa.Table.from_batches([x])
            t = pa.concat_tables([held, t]).combine_chunks() if held is not None else t
            k = t.column("k").to_numpy()
            new = np.flatnonzero(k[1:] != k[:-1]) + 1
            if not len(new):
                held = t
                continue
            held = t.slice(int(new[-1]))
            done = t.slice(0, int(new[-1]))
            yield from links(done.column("fp").to_numpy(), done.column("tid").to_pylist(), new[:-1].tolist())
        if held is not None and held.num_rows:
            yield from links(held.column("fp").to_numpy(), held.column("tid").to_pylist(), [])

    out = map_batches(dealt, walk, "a binary, b binary")
    for s in stars:
        out = out.unionByName(s)
    return out.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct() if not stars else out.where("a <> b").distinct()


def rest(keys: DataFrame, label: DataFrame, radius: int, tile: int = 4096) -> DataFrame:
    """(a binary, b binary): every pair of texts that share a band (keys: tid, fp, k) and lie within the radius, but not in one class of `label` (v, label); distinct.

    Only shards with several classes are looked at. A shard of more than `tile` texts is cut into parts by hash, and each pair of parts is a task's own.
    """
    x = keys.join(label.withColumnRenamed("v", "tid"), "tid", "left").select("k", "fp", "tid", F.coalesce("label", "tid").alias("c"))
    x = written(x, "classed-keys")
    sizes = x.groupBy("k").agg(F.count(F.lit(1)).alias("n"), F.min("c").alias("c0"), F.max("c").alias("c1")).where("c0 < c1")
    sizes = written(sizes.select("k", F.ceil(F.col("n") / tile).cast("int").alias("p")), "mixed-shards")
    x = x.join(sizes, "k").withColumn("part", F.pmod(F.xxhash64(F.lit("part"), "tid"), F.col("p")).cast("int"))
    # a text goes to each tile (i, j), i <= j, of which its part is a side
    x = x.select("k", "fp", "tid", "c", "part", F.explode(F.sequence(F.lit(0), F.col("p") - 1)).alias("o"))
    x = x.select("k", F.least("part", "o").alias("i"), F.greatest("part", "o").alias("j"), "part", "fp", "tid", "c")
    dealt = x.repartition("k", "i", "j").sortWithinPartitions("k", "i", "j", "part")

    def pairs(t):
        fp = t.column("fp").to_numpy().view(np.uint64)
        tid = t.column("tid").to_pylist()
        c = np.unique(np.array([bytes(v) for v in t.column("c").to_pylist()], object), return_inverse=True)[1]
        i, j, part = (int(t.column("i")[0].as_py()), int(t.column("j")[0].as_py()), t.column("part").to_numpy())
        left, right = np.flatnonzero(part == i), np.flatnonzero(part == j)
        for at in range(0, len(left), 256):
            rows = left[at : at + 256]
            near = (np.bitwise_count(fp[rows][:, None] ^ fp[right][None, :]) <= radius) & (c[rows][:, None] != c[right][None, :])
            p, q = np.nonzero(near)
            p, q = rows[p], right[q]
            if i == j:
                p, q = p[p < q], q[p < q]
            for s in range(0, len(p), 10_000):
                two = [sorted((tid[m], tid[n])) for m, n in zip(p[s : s + 10_000].tolist(), q[s : s + 10_000].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array([m for m, _ in two], pa.binary()), pa.array([n for _, n in two], pa.binary())], ["a", "b"])

    def walk(batches):
        held = None
        for b in batches:
            t = pa.Table.from_batches([b])
            t = pa.concat_tables([held, t]).combine_chunks() if held is not None else t
            k, i, j = (t.column(n).to_numpy() for n in ("k", "i", "j"))
            new = np.flatnonzero((k[1:] != k[:-1]) | (i[1:] != i[:-1]) | (j[1:] != j[:-1])) + 1
            held = t
            if len(new):
                for s, e in zip([0, *new[:-1].tolist()], new.tolist(), strict=True):
                    if e - s > 1:
                        yield from pairs(t.slice(s, e - s))
                held = t.slice(int(new[-1]))
        if held is not None and held.num_rows > 1:
            yield from pairs(held)

    return map_batches(dealt, walk, "a binary, b binary").distinct()


def verified(pairs: DataFrame, docs: DataFrame, of: DataFrame, width: int, least: float) -> DataFrame:
    """The pairs (a, b) whose texts' shingle sets have a Jaccard similarity of at least `least`.

    One row of each text that is in a pair is looked up. A text of very many pairs goes to several tasks.
    """
    asked = pairs.select(F.col("a").alias("tid")).unionByName(pairs.select(F.col("b").alias("tid"))).distinct()
    chosen = of.join(asked, "tid", "left_semi").select(F.col("tid").alias("_t"), F.col("least").alias("_d"))
    rows = with_tid(docs.select("doc_id", "text"))
    # never a broadcast join: it would put both maps over texts into one stage, with two Python processes for each task
    rows = rows.join(chosen.hint("merge"), (F.col("tid") == F.col("_t")) & F.col("doc_id").eqNullSafe(F.col("_d")), "left_semi")

    def hashed(b: pa.RecordBatch) -> pa.RecordBatch:
        sets = [np.unique(shingle_hashes(words(t), width)).view(np.int64) for t in raw_texts(b.column("text"))]
        return pa.RecordBatch.from_arrays([b.column("tid"), pa.array(sets, pa.list_(pa.int64()))], ["tid", "s"])

    sets = written(map_text(rows.select("tid", "text"), hashed, "tid binary, s array<bigint>"), "shingle-sets")
    many = written(pairs.groupBy("a").agg(F.ceil(F.count(F.lit(1)) / STAR).alias("n")).where("n > 1"), "stars")
    salted = pairs.join(_small(many), "a", "left").withColumn("salt", F.pmod(F.xxhash64("b"), F.coalesce("n", F.lit(1).cast("bigint")))).drop("n")
    x = salted.join(sets.select(F.col("tid").alias("b"), F.col("s").alias("sb")), "b")
    whole = sets.join(_small(many.withColumnRenamed("a", "tid")), "tid", "left")
    whole = whole.select(F.col("tid").alias("a"), F.col("s").alias("sa"), F.explode(F.sequence(F.lit(0).cast("bigint"), F.coalesce("n", F.lit(1).cast("bigint")) - 1)).alias("salt"))
    x = x.join(whole, ["a", "salt"])
    both = F.size(F.array_intersect("sa", "sb"))
    return x.select("a", "b", (both / (F.size("sa") + F.size("sb") - both)).alias("j")).where(F.col("j") >= least).select("a", "b").distinct()


def similar_classes(docs: DataFrame, width: int = 5, least: float = 0.8, radius: int = 18, hot: int = 512) -> tuple[DataFrame, DataFrame]:
    """((doc_id, tid) of each row, (tid, least doc_id, class) of each distinct text): equal classes exactly within a component of verified links."""
    rows = written(sketches(docs, width), "sketches")
    of = rows.groupBy("tid").agg(F.min("doc_id").alias("least"), F.first("fp").alias("fp"), F.first("bands").alias("bands"))
    of = written(of, "texts")
    keys = band_keys(of)
    pairs = written(candidates(keys, radius, hot), "candidates")
    links = written(verified(pairs, docs, of, width, least), "links")
    label = written(components(links), "quick-classes")
    more = rest(keys, label, radius)
    more = written(more.join(pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")), ["a", "b"], "left_anti"), "rest")
    if more.limit(1).count():
        found = written(verified(more, docs, of, width, least), "more-links")
        if found.limit(1).count():
            label = components(links.unionByName(found))
    return rows.select("doc_id", "tid"), of.join(label.withColumnRenamed("v", "tid"), "tid", "left").select("tid", "least", F.coalesce("label", "tid").alias("class"))


def _first(*names: str) -> Column:
    """The order of a class's texts: smallest id first, no id last, then the text's hash."""
    return F.min(F.struct(F.col(names[0]).isNull().alias("n"), *names))


def one_of_each(docs: DataFrame, width: int = 5, least: float = 0.8, radius: int = 18, hot: int = 512) -> DataFrame:
    """The rows of docs, all columns, one of each class of similar texts."""
    rows, of = similar_classes(docs, width, least, radius, hot)
    stay = written(of.groupBy("class").agg(_first("least", "tid").alias("m")).select(F.col("m.tid").alias("_t"), F.col("m.least").alias("_d")), "stay")
    same = lambda t, d: (F.col("tid") == F.col(t)) & F.col("doc_id").eqNullSafe(F.col(d))
    repeated = rows.groupBy("tid", "doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").join(stay, same("_t", "_d"), "left_semi").select(F.col("tid").alias("_r"))
    repeated = written(repeated, "repeated")
    names = {c: f"_in_{i}" for i, c in enumerate(docs.columns) if c not in ("doc_id", "text")}
    kept = with_tid(docs.withColumnsRenamed(names)).join(stay, same("_t", "_d"), "left_semi")
    if repeated.limit(1).count():
        again = F.col("tid") == F.col("_r")
        kept = kept.join(_small(repeated), again, "left_anti").unionByName(kept.join(_small(repeated), again, "left_semi").dropDuplicates(["tid"]))
    return kept.drop("tid").withColumnsRenamed({v: k for k, v in names.items()}).select(*docs.columns)
