"""Best-fit packing of tokenised documents after a Martello-Toth dominance reduction.

Documents are tokenised, closed by an end token and cut into pieces of at most `capacity` tokens; only longer ones are cut.
What has to be packed is then a histogram of piece lengths, at most `capacity` numbers, however many pieces there are. On it
the reduction fixes sets which dominate every alternative for one of their members: a piece with which nothing fits; a
piece and its exact complement; a piece with the largest mate when only one mate fits, or when that mate is at
least as large as the best two together and no third fits. It repeats until nothing changes; best fit in decreasing order
packs the rest. Both work on whole runs of equal lengths, so the plan has runs and not pieces, and is small enough to
broadcast: its size depends on `capacity` alone. Pieces find their place by their rank among those of equal length. Ranks are made in
slots of a length, so a length that a third of all pieces have is dealt to many tasks.

Tokens: texts are cut at ASCII white space, which no rule of the tokenizer crosses, and each worker keeps the ids of chunks it
has seen in a bounded table.

Defined cases: a null text is an empty one, whose only token is the end token. Repeated rows, null doc_ids and ties are
packed like other rows. Extra columns are ignored. An empty table gives an empty result.
"""

from __future__ import annotations

import json
import re
import sys
import zlib
from array import array
from bisect import bisect_left, insort

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import map_text, raw_texts, ship, worker_state, written

#: Chunks of text whose ids a worker keeps (in each of two generations), and the longest of them.
KNOWN_CHUNKS, CHUNK_BYTES = 150_000, 48
assert sys.byteorder == "little" and array("I").itemsize == 4


def byte_letters() -> dict[int, str]:
    """The byte-level alphabet: printable Latin-1 characters stand for their bytes, the others are numbered from 256 on."""
    own = {*range(33, 127), *range(161, 173), *range(174, 256)}
    rest = (b for b in range(256) if b not in own)
    return {b: chr(256 + i) for i, b in enumerate(rest)}


class Kept:
    """A bounded table of two generations: what is looked up again moves to the younger, the older goes when that is full."""

    def __init__(self, most: int):
        self.young: dict = {}
        self.old: dict = {}
        self.most = most

    def get(self, key):
        v = self.young.get(key)
        if v is None and (v := self.old.get(key)) is not None:
            self.put(key, v)
        return v

    def put(self, key, value) -> None:
        if len(self.young) >= self.most:
            self.old, self.young = self.young, {}
        self.young[key] = value


class Encoder:
    """Little-endian unsigned 32-bit ids of texts, as the whole tokenizer gives them.

    Chunks between ASCII white space are looked up. New ones of ASCII and Latin-1 letters, for which the tokenizer's normal form is
    to lower each letter, are cut as its pre-tokenizer does and go to its BPE model piece by piece; others go through all of the tokenizer.
    Tokenizer files with other rules than these always go through all of it.
    """

    plain = re.compile(r"[!-~À-ÖØ-öø-ÿ]+")
    cut = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-zß-öø-ÿ]+|[0-9]|[^a-zß-öø-ÿ0-9]+")
    # fixed values: the rules for which the short way holds
    rule = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.chunks, self.pieces, self.letters = Kept(KNOWN_CHUNKS), Kept(KNOWN_CHUNKS), byte_letters()
        spec = json.loads(self.tok.to_str())
        self.specials = [x["content"].encode() for x in spec["added_tokens"]]
        kinds = [x.get("type") for x in (spec["normalizer"] or {}).get("normalizers", [])]
        steps = (spec["pre_tokenizer"] or {}).get("pretokenizers", [])
        self.short = kinds == ["NFC", "Replace", "Lowercase"] and [x.get("type") for x in steps] == ["Split", "ByteLevel"] and steps[0]["pattern"] == {"Regex": self.rule} and not any(x["normalized"] or x["lstrip"] or x["rstrip"] or x["single_word"] for x in spec["added_tokens"])
        if self.tok.pre_tokenizer is not None and not self.short:
            raise ValueError("this tokenizer's rules may cross white space")

    def piece(self, p: str) -> bytes:
        ids = self.pieces.get(p)
        if ids is None:
            ids = array("I", [t.id for t in self.tok.model.tokenize(p if p.isascii() else p.encode().decode("latin-1").translate(self.letters))]).tobytes()
            if len(p) <= CHUNK_BYTES:
                self.pieces.put(p, ids)
        return ids

    def new(self, chunk: bytes, special: bool) -> bytes:
        text = chunk.decode()
        if text.isascii() and text.isalpha():
            out = self.piece(text.lower())
        elif (special and any(x in chunk for x in self.specials)) or not self.plain.fullmatch(text):
            out = array("I", self.tok.encode(text, add_special_tokens=False).ids).tobytes()
        else:
            out = b"".join(map(self.piece, self.cut.findall(text.lower())))
        if len(chunk) <= CHUNK_BYTES:
            self.chunks.put(chunk, out)
        return out

    def __call__(self, text: bytes) -> bytes:
        chunks = text.split()
        ids = list(map(self.chunks.young.get, chunks))
        if None in ids:
            special = any(x in text for x in self.specials)
            for i, x in enumerate(ids):
                if x is None:
                    x = self.chunks.get(chunks[i])
                    ids[i] = self.new(chunks[i], special) if x is None else x
        return b"".join(ids)


def encoder(path: str) -> Encoder:
    """The tokenizer file's encoder, one per process."""
    return worker_state(("encoder", path), lambda: Encoder(path))


def pieces(docs: DataFrame, tokenizer: str, capacity: int = 4096, end_id: int = 1) -> DataFrame:
    """(doc_id, piece int, start, length, ids_crc32 bigint): each document's token sequence cut at multiples of capacity."""
    kind = dict(docs.dtypes)["doc_id"]

    def cut(b: pa.RecordBatch) -> pa.RecordBatch:
        encode, end = encoder(tokenizer), np.uint32(end_id).astype("<u4").tobytes()
        row, piece, start, length, crc = [], [], [], [], []
        for i, t in enumerate(raw_texts(b.column("text"))):
            ids = encode(t) + end
            for k, at in enumerate(range(0, len(ids), 4 * capacity)):
                part = ids[at : at + 4 * capacity]
                row.append(i), piece.append(k), start.append(at // 4), length.append(len(part) // 4), crc.append(zlib.crc32(part))
        return pa.RecordBatch.from_arrays([b.column("doc_id").take(pa.array(row, pa.int64())), pa.array(piece, pa.int32()), *(pa.array(x, pa.int64()) for x in (start, length, crc))], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return map_text(docs.select("doc_id", "text"), cut, f"doc_id {kind}, piece int, start bigint, length bigint, ids_crc32 bigint")


def reduce_instance(count: dict[int, int], capacity: int) -> tuple[list[tuple[tuple[tuple[int, int], ...], int]], dict[int, int]]:
    """Bins fixed by dominance, as (((length, how many), ...), number of such bins), and the pieces that are left."""
    left = {w: n for w, n in count.items() if n}
    sizes = sorted(left)
    fixed: list = []

    def use(w: int, n: int) -> None:
        left[w] -= n
        if not left[w]:
            del left[w]
            del sizes[bisect_left(sizes, w)]

    def smallest(n: int, but: int) -> list[int]:
        """The n smallest pieces when one of length `but` is set aside."""
        out: list[int] = []
        for s in sizes:
            out += [s] * min(n - len(out), left[s] - (s == but))
            if len(out) == n:
                break
        return out

    def mate(w: int, room: int) -> int | None:
        i = bisect_left(sizes, room + 1) - 1
        while i >= 0 and sizes[i] == w and left[w] < 2:
            i -= 1
        return sizes[i] if i >= 0 else None

    def best_two(w: int, room: int) -> int:
        """The largest total of two pieces within room."""
        best, lo, hi = 0, 0, bisect_left(sizes, room + 1) - 1
        while lo <= hi:
            total = sizes[lo] + sizes[hi]
            need = 2 if lo == hi else 1
            if total > room or left[sizes[hi]] - (sizes[hi] == w) < need:
                hi -= 1
            else:
                best = max(best, total)
                lo += 1
        return best

    changed = True
    while changed:
        changed = False
        for w in list(reversed(sizes)):
            while left.get(w):
                room = capacity - w
                low = smallest(3, w)
                if not low or low[0] > room:
                    fixed.append((((w, 1),), left[w]))
                    use(w, left[w])
                    changed = True
                    break
                m = mate(w, room)
                one = len(low) < 2 or low[0] + low[1] > room
                two = len(low) < 3 or sum(low) > room
                if not (m == room or one or two and m >= best_two(w, room)):
                    break
                if m == w:
                    n = left[w] // 2
                    fixed.append((((w, 2),), n))
                    use(w, 2 * n)
                else:
                    # the smallest pieces only grow as they are used, so what holds for one holds for the run of them
                    n = min(left[w], left[m])
                    fixed.append((((w, 1), (m, 1)), n))
                    use(w, n)
                    use(m, n)
                changed = True
    return fixed, left


def best_fit(count: dict[int, int], capacity: int) -> list[tuple[tuple[tuple[int, int], ...], int]]:
    """Best fit in decreasing order on whole runs: bins as (((length, how many), ...), number of such bins)."""
    rooms: list[int] = []
    of: dict[int, list] = {}
    full: list = []

    def put(room: int, content: tuple, n: int) -> None:
        if not n:
            return
        if room == 0:
            full.append((content, n))
            return
        if room not in of:
            insort(rooms, room)
            of[room] = []
        of[room].append((content, n))

    for w in sorted(count, reverse=True):
        n = count[w]
        while n:
            i = bisect_left(rooms, w)
            if i == len(rooms):
                k = capacity // w
                put(capacity - k * w, ((w, k),), n // k)
                if n % k:
                    put(capacity - (n % k) * w, ((w, n % k),), 1)
                break
            room = rooms[i]
            content, bins = of[room].pop()
            if not of[room]:
                del of[room]
                del rooms[i]
            k = room // w
            all_k = min(bins, n // k)
            put(room - k * w, (*content, (w, k)), all_k)
            n -= all_k * k
            bins -= all_k
            if bins and n:
                put(room - n * w, (*content, (w, n)), 1)
                bins -= 1
                n = 0
            put(room, content, bins)
    return full + [x for room in rooms for x in of[room]]


def plan(count: dict[int, int], capacity: int) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For each length, runs of ranks: (first rank, sequence of that rank, offset in its sequence)."""
    fixed, left = reduce_instance(count, capacity)
    runs: dict[int, list] = {}
    used: dict[int, int] = {}
    base = 0
    for content, bins in fixed + best_fit(left, capacity):
        at = 0
        for w, k in content:
            for _ in range(k):
                runs.setdefault(w, []).append((used.get(w, 0), base, at))
                used[w] = used.get(w, 0) + bins
                at += w
        base += bins
    assert used == {w: n for w, n in count.items() if n}, "each piece has one place"
    return {w: tuple(np.array(x, np.int64) for x in zip(*r, strict=True)) for w, r in runs.items()}


def pack(docs: DataFrame, tokenizer: str, capacity: int = 4096, end_id: int = 1) -> DataFrame:
    """The columns of pieces(), sequence_id and offset (bigint): each piece's place; places in a sequence leave no gap."""
    spark = docs.sparkSession
    cut = written(pieces(docs, tokenizer, capacity, end_id).withColumn("_row", F.monotonically_increasing_id()), "pieces")
    count = {r.length: r.n for r in cut.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most `capacity` rows
    slots = max(256, min(1 << 16, sum(count.values()) // 5_000_000))
    ship(spark)
    places = spark.sparkContext.broadcast(plan(count, capacity))
    rows = cut.withColumn("_slot", F.pmod(F.xxhash64("_row"), F.lit(slots)))
    before = rows.groupBy("length", "_slot").agg(F.count(F.lit(1)).alias("_n"))
    before = before.select("length", "_slot", (F.sum("_n").over(Window.partitionBy("length").orderBy("_slot")) - F.col("_n")).alias("_before"))
    own = F.row_number().over(Window.partitionBy("length", "_slot").orderBy("_row")) - 1
    ranked = rows.withColumn("_own", own).join(before, ["length", "_slot"])
    names = ["doc_id", "piece", "start", "length", "ids_crc32"]
    ranked = ranked.select(*names, (F.col("_own") + F.col("_before")).alias("_rank"))

    def place(batches):
        for b in batches:
            if not b.num_rows:
                continue
            length, rank = (b.column(c).to_numpy(zero_copy_only=False) for c in ("length", "_rank"))
            seq, off = np.empty((2, len(rank)), np.int64)
            order = np.argsort(length, kind="stable")
            cuts = np.flatnonzero(np.diff(length[order])) + 1
            for at in np.split(order, cuts):
                first, base, offset = places.value[int(length[at[0]])]
                i = np.searchsorted(first, rank[at], "right") - 1
                seq[at], off[at] = base[i] + rank[at] - first[i], offset[i]
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in names), pa.array(seq), pa.array(off)], [*names, "sequence_id", "offset"])

    kind = dict(docs.dtypes)["doc_id"]
    return ranked.mapInArrow(place, f"doc_id {kind}, piece int, start bigint, length bigint, ids_crc32 bigint, sequence_id bigint, offset bigint")
