"""SimHash near-duplicates: 64-bit fingerprints linked within a small Hamming radius by BK-trees.

Fingerprint: the text with A-Z lowered, its words (runs of bytes other than space and \x09-\x0D), their shingles of
`width` words with repeats (fewer words: the whole sequence); XXH64 (seed 42) of each shingle; a bit is set if it is
set in over half of the hashes. A text without words has fingerprint 0, which links like any other.

Links: distinct fingerprints are dealt to shards, so that two which differ in at most `radius` bits meet in a shard:
64 bits are cut into blocks, more than `radius` of them, and each choice of blocks which may be equal makes a key. Each
shard builds a BK-tree and walks it: only edges whose distance is within `radius` of the query's. A component is taken
out of the tree as it is found, so a shard gives a link per fingerprint and not one per pair. Shards with more than
`hot` members are dealt again by the bits that their key leaves free, which loses no link. What still shares both keys agrees in all but
a few bits, so its size is bounded by their number and not by the table's. Trees stay in the task that
owns the shard: to broadcast them would need memory that grows with the table.

Components: links are contracted round by round under random priorities, with a written table after each round.

Defined cases: null and empty texts have fingerprint 0. Rows with a null doc_id get the component of their text;
the smallest non-null doc_id names it (null if there is none). Repeated rows each get a row. Extra columns are ignored.
"""

from __future__ import annotations

from itertools import combinations, repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_text, raw_texts, ship, written

SEED = 42
MASK = (1 << 64) - 1
#: Rows of one fingerprint from which on its class is broadcast instead of joined, and how many such fingerprints may be.
HOT_ROWS, HOT_FINGERPRINTS = 20_000, 100_000


def fingerprint(text: bytes, width: int = 3) -> int:
    """The unsigned 64-bit fingerprint of UTF-8 bytes."""
    w = text.lower().split()  # bytes: A-Z alone are lowered, ASCII white space alone divides
    if not w:
        return 0
    shingles = list(map(b" ".join, zip(*(w[i:] for i in range(width)), strict=False))) if len(w) >= width else [b" ".join(w)]
    set_in = np.zeros(64, np.int64)
    for at in range(0, len(shingles), 1 << 16):
        part = shingles[at : at + (1 << 16)]
        h = np.frombuffer(b"".join(map(xxhash.xxh64_digest, part, repeat(SEED))), np.uint8).reshape(-1, 8)
        set_in += np.unpackbits(h, axis=1).sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * set_in > len(shingles)).tobytes(), "big")


def fingerprints(docs: DataFrame, width: int = 3, carry: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The carried columns and fp (bigint, the fingerprint's bits)."""
    carry = tuple(c for c in carry if c != "fp")
    types = dict(docs.dtypes)

    def run(b: pa.RecordBatch) -> pa.RecordBatch:
        fp = np.array([fingerprint(t, width) for t in raw_texts(b.column("text"))], np.uint64).view(np.int64)
        return pa.RecordBatch.from_arrays([*(b.column(c) for c in carry), pa.array(fp)], [*carry, "fp"])

    return map_text(docs.select(*dict.fromkeys([*carry, "text"])), run, ", ".join([*(f"`{c}` {types[c]}" for c in carry), "fp bigint"]))


class BKTree:
    """Children keyed by their Hamming distance to the parent; found members can be taken out."""

    def __init__(self, codes: list[int]):
        self.codes = codes
        self.parent = [-1] * len(codes)
        self.children: list[dict[int, int] | None] = [None] * len(codes)
        self.live = [1] * len(codes)
        self.alive = [True] * len(codes)
        for i in range(1, len(codes)):
            c, at = codes[i], 0
            while True:
                self.live[at] += 1
                d = (c ^ codes[at]).bit_count()
                kids = self.children[at]
                if kids is None:
                    kids = self.children[at] = {}
                nxt = kids.get(d)
                if nxt is None:
                    kids[d] = i
                    self.parent[i] = at
                    break
                at = nxt

    def take(self, i: int) -> None:
        self.alive[i] = False
        while i >= 0:
            self.live[i] -= 1
            i = self.parent[i]

    def near(self, code: int, radius: int) -> list[int]:
        """Members still in the tree within radius of code."""
        if not self.codes or not self.live[0]:
            return []
        hits, todo = [], [0]
        codes, children, live, alive = self.codes, self.children, self.live, self.alive
        while todo:
            i = todo.pop()
            d = (code ^ codes[i]).bit_count()
            if d <= radius and alive[i]:
                hits.append(i)
            kids = children[i]
            if kids:
                if len(kids) <= 2 * radius + 1:
                    todo += [j for e, j in kids.items() if d - radius <= e <= d + radius and live[j]]
                else:
                    todo += [j for e in range(d - radius, d + radius + 1) if (j := kids.get(e)) is not None and live[j]]
        return hits

    def forest(self, radius: int) -> list[tuple[int, int]]:
        """(member, root) for each member but the roots of the components in this tree. Empties the tree."""
        out = []
        for root in range(len(self.codes)):
            if not self.alive[root]:
                continue
            self.take(root)
            todo = [root]
            while todo:
                for j in self.near(self.codes[todo.pop()], radius):
                    self.take(j)
                    out.append((j, root))
                    todo.append(j)
        return out


def block_masks(bits: list[int], blocks: int, equal: int) -> list[int]:
    """A mask for each choice of `equal` out of `blocks` runs of the given bit positions."""
    cuts = [bits[len(bits) * i // blocks : len(bits) * (i + 1) // blocks] for i in range(blocks)]
    return [sum(1 << b for i in pick for b in cuts[i]) for pick in combinations(range(blocks), equal)]


def plan_masks(n: int, radius: int, members: int = 64) -> list[int]:
    """The fewest masks for which a shard of n random fingerprints has about `members` at most."""
    for blocks in range(radius + 1, 64):
        masks = block_masks(list(range(64)), blocks, blocks - radius)
        if n <= members << min(m.bit_count() for m in masks) or len(masks) > 100:
            return masks
    raise ValueError("radius too large")


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def near_links(fps: DataFrame, radius: int = 3, hot: int = 256, n: int | None = None) -> DataFrame:
    """(a bigint, b bigint): for distinct fingerprints fps(fp), links that connect all within radius, directly or by steps within it."""
    ship(fps.sparkSession)
    masks = plan_masks(fps.count() if n is None else n, radius)

    shard = F.array(*[F.struct(F.lit(_signed(m)).alias("m"), F.col("fp").bitwiseAND(F.lit(_signed(m))).alias("k")) for m in masks])
    rows = fps.select("fp", F.inline(shard))
    sizes = rows.groupBy("m", "k").agg(F.count(F.lit(1)).alias("c")).where("c > 1")
    sizes = written(sizes, "shard-sizes")
    cold = rows.join(sizes.where(F.col("c") <= hot).select("m", "k"), ["m", "k"]).select("fp", "m", "k", F.lit(0).cast("bigint").alias("m2"))
    again = rows.join(sizes.where(F.col("c") > hot).select("m", "k"), ["m", "k"])
    finer = None
    for m in masks:
        free = [b for b in range(64) if not m >> b & 1]
        sub = [F.struct((F.lit(_signed(m)).bitwiseOR(F.lit(_signed(s)))).alias("m2")) for s in block_masks(free, radius + 1, 1)]
        part = again.where(F.col("m") == _signed(m)).select("fp", "m", F.inline(F.array(*sub))).select("fp", "m", F.col("fp").bitwiseAND(F.col("m2")).alias("k"), "m2")
        finer = part if finer is None else finer.unionByName(part)
    shards = cold.unionByName(finer.select("fp", "m", "k", "m2")) if sizes.where(F.col("c") > hot).limit(1).count() else cold
    dealt = shards.repartition(F.col("m"), F.col("m2"), F.col("k")).sortWithinPartitions("m", "m2", "k", "fp")

    def walk(batches):
        rest = None
        for b in batches:
            x = np.stack([b.column(c).to_numpy(zero_copy_only=False) for c in ("m", "m2", "k", "fp")]) if b.num_rows else np.empty((4, 0), np.int64)
            if rest is not None:
                x = np.concatenate([rest, x], axis=1)
            new = np.flatnonzero((x[:3, 1:] != x[:3, :-1]).any(0)) + 1
            if not len(new):
                rest = x
                continue
            rest = x[:, new[-1] :]
            yield from links(x[3, : new[-1]], new[:-1])
        if rest is not None and rest.shape[1]:
            yield from links(rest[3], np.empty(0, np.int64))

    def links(fp, cuts):
        a, b = [], []
        starts, ends = [0, *cuts.tolist()], [*cuts.tolist(), len(fp)]
        codes = fp.view(np.uint64).tolist()
        for s, e in zip(starts, ends, strict=True):
            if e - s < 2:
                continue
            for i, j in BKTree(codes[s:e]).forest(radius):
                a.append(codes[s + i])
                b.append(codes[s + j])
        if a:
            yield pa.RecordBatch.from_arrays([pa.array(np.array(x, np.uint64).view(np.int64)) for x in (a, b)], ["a", "b"])

    return dealt.mapInArrow(walk, "a bigint, b bigint")


def components(links: DataFrame, rounds: int = 200) -> DataFrame:
    """(v bigint, label bigint) for each end of a link: equal labels exactly within a connected component.

    In each round a vertex takes the neighbour (or itself) of least random priority; links are rewritten between those.
    Counts and minima are combined before they are shuffled, and no neighbour list is ever gathered.
    """
    edges = written(links.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a <> b").distinct(), "links")
    label = None
    for r in range(rounds):
        if not edges.limit(1).count():
            break
        both = edges.select("a", "b").unionAll(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        rank = lambda c: F.xxhash64(F.lit(r), c)  # noqa: B023, E731
        best = both.groupBy("a").agg(F.min(F.struct(rank(F.col("b")).alias("p"), F.col("b").alias("v"))).alias("n"))
        own = F.struct(rank(F.col("a")).alias("p"), F.col("a").alias("v"))
        step = written(best.select(F.col("a").alias("v"), F.least(own, F.col("n"))["v"].alias("to")), "steps")
        if label is None:
            label = step.select("v", F.col("to").alias("label"))
        else:
            s = step.select(F.col("v").alias("label"), "to")
            label = label.join(s, "label", "left").select("v", F.coalesce("to", "label").alias("label"))
        label = written(label, "labels")
        x = edges.join(step.select(F.col("v").alias("a"), F.col("to").alias("ta")), "a").join(step.select(F.col("v").alias("b"), F.col("to").alias("tb")), "b")
        edges = written(x.where("ta <> tb").select(F.least("ta", "tb").alias("a"), F.greatest("ta", "tb").alias("b")).distinct(), "links")
    else:
        raise RuntimeError("components did not converge")
    return label if label is not None else edges.select(F.col("a").alias("v"), F.col("b").alias("label"))


def classes(docs: DataFrame, radius: int = 3, width: int = 3, hot: int = 256) -> DataFrame:
    """(doc_id, fp bigint, class bigint, component_id) for each row of docs: equal classes exactly within a component."""
    rows = written(fingerprints(docs, width), "fingerprints")
    of = written(rows.groupBy("fp").agg(F.min("doc_id").alias("least"), F.count(F.lit(1)).alias("n")), "distinct-fingerprints")
    label = components(near_links(of.select("fp"), radius, hot))
    named = of.join(label.withColumnRenamed("v", "fp"), "fp", "left").select("fp", "least", F.coalesce("label", "fp").alias("class"))
    least = named.groupBy("class").agg(F.min("least").alias("component_id"))
    by_fp = written(named.join(least, "class").select("fp", "class", "component_id"), "named-fingerprints")
    hot_fps = of.where(F.col("n") > HOT_ROWS).select("fp")
    many = hot_fps.limit(HOT_FINGERPRINTS + 1).count()
    out = ["doc_id", "fp", "class", "component_id"]
    if not 0 < many <= HOT_FINGERPRINTS:
        return rows.join(by_fp, "fp").select(*out)
    # all empty texts, for one, share a fingerprint: their rows stay where they are
    hot_fps = F.broadcast(hot_fps)
    there = rows.join(hot_fps, "fp", "left_semi").join(F.broadcast(by_fp.join(hot_fps, "fp", "left_semi")), "fp").select(*out)
    return there.unionByName(rows.join(hot_fps, "fp", "left_anti").join(by_fp, "fp").select(*out))


def near_duplicates(docs: DataFrame, radius: int = 3, width: int = 3, hot: int = 256) -> DataFrame:
    """(doc_id, fingerprint string of 16 hex digits, component_id) for each row of docs."""
    out = classes(docs, radius, width, hot)
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def one_of_each(docs: DataFrame, radius: int = 3, width: int = 3, hot: int = 256) -> DataFrame:
    """The rows of docs, all columns, without near-duplicates: of a class the row with the smallest doc_id stays (without any ids, any one row).

    Fingerprints, not texts, are grouped. Texts are shuffled once, by (doc_id, fingerprint); only rows which repeat both go through another step.
    """
    found = written(classes(docs, radius, width, hot), "classes")
    gone = found.where("component_id is not null and not doc_id <=> component_id").select("doc_id", "fp").distinct()
    stay = found.where("doc_id <=> component_id")
    again = stay.groupBy("doc_id", "fp").agg(F.count(F.lit(1)).alias("n"), F.min("class").alias("class")).where("n > 1 or doc_id is null").select("doc_id", "fp", "class")
    # of one doc_id with several fingerprints in its class, the smallest fingerprint stays
    several = stay.select("doc_id", "fp", "class").distinct().groupBy("doc_id", "class").agg(F.min("fp").alias("least"), F.count(F.lit(1)).alias("n")).where("n > 1")
    names = {c: f"_in_{i}" for i, c in enumerate(docs.columns) if c not in ("doc_id", "text")}
    safe = docs.withColumnsRenamed(names)
    rows = fingerprints(safe, width, carry=tuple(safe.columns))
    same = lambda a, b: a["doc_id"].eqNullSafe(b["doc_id"]) & (a["fp"] == b["fp"])
    gone = gone.unionAll(stay.join(several, ["doc_id", "class"]).where("fp <> least").select("doc_id", "fp").distinct())
    rows = rows.join(gone, same(rows, gone), "left_anti")
    if again.limit(1).count():
        once = rows.join(again, same(rows, again), "left_anti")
        more = rows.join(again.withColumnRenamed("doc_id", "_id").withColumnRenamed("fp", "_fp"), F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("fp") == F.col("_fp")))
        rows = once.unionByName(more.dropDuplicates(["class"]).select(*once.columns))
    return rows.drop("fp").withColumnsRenamed({v: k for k, v in names.items()}).select(*docs.columns)
