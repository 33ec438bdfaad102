"""Line deduplication: lines whose normalised form occurs in many documents are dropped everywhere.

A line is a maximal run without "\n". Its key is the line without white space (space, \t, \n, \v, \f, \r) at
both ends and with A-Z lowered. Keys with at least `min_chars` code points which occur in at least `min_docs`
documents lose all their lines; the others stay in place, joined by "\n".

Defined cases: a null or empty text is one empty line (n_lines 1, nothing dropped as its key is too short, text
""). A row is a document: a repeated row counts again, whatever its doc_id, null included. Extra columns are
ignored unless named in `carry`; a carried column with the name of an output is replaced by the output. An empty
table gives an empty result.
"""

from __future__ import annotations

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_text, raw_texts, written

OUTPUTS = ("text", "n_lines", "n_dropped")
SPACE = b" \t\n\v\f\r"
#: Frequent keys are broadcast up to this number (about 100 bytes each in a worker); beyond it they are joined.
BROADCAST_KEYS = 300_000


def key_hash(line: bytes, min_chars: int = 1) -> bytes | None:
    """128 bits that stand for the line's key; None for keys which are too short."""
    key = line.strip(SPACE).lower()  # bytes.lower changes A-Z alone
    if not key or (len(key) < 4 * min_chars and len(key.decode("utf-8", "replace")) < min_chars):
        return None
    return xxhash.xxh3_128_digest(key)


def frequent_keys(docs: DataFrame, min_docs: int = 10, min_chars: int = 1) -> DataFrame:
    """(key binary): hashes of keys in at least min_docs documents. Each document adds a key once; counts are combined before the shuffle."""

    def explode(b: pa.RecordBatch) -> pa.RecordBatch:
        out: list[bytes] = []
        for t in raw_texts(b.column("text")):
            found = {key_hash(x, min_chars) for x in t.split(b"\n")}
            found.discard(None)
            out += found
        return pa.RecordBatch.from_arrays([pa.array(out, pa.binary())], ["key"])

    keys = map_text(docs.select("text"), explode, "key binary")
    return keys.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= min_docs).select("key")


def drop_frequent_lines(docs: DataFrame, min_docs: int = 10, min_chars: int = 1, carry: tuple[str, ...] = ("doc_id",), broadcast_keys: int = BROADCAST_KEYS) -> DataFrame:
    """The carried columns, then text (kept lines), n_lines (before dropping) and n_dropped, a row for each row of docs."""
    carry = tuple(c for c in carry if c not in OUTPUTS)
    types = dict(docs.dtypes)
    keys = written(frequent_keys(docs, min_docs, min_chars), "line-keys")
    schema = ", ".join([*(f"`{c}` {types[c]}" for c in carry), "text string, n_lines bigint, n_dropped bigint"])
    if keys.count() <= broadcast_keys:
        known = docs.sparkSession.sparkContext.broadcast(frozenset(bytes(r[0]) for r in keys.collect()))
        rows, found = docs.select(*carry, "text"), None
    else:
        known, found = None, "_frequent"
        rows = _with_frequent(docs, keys, carry, min_chars)

    def apply(b: pa.RecordBatch) -> pa.RecordBatch:
        kept, before, gone = [], [], []
        own = b.column(found).to_pylist() if found else None
        for i, t in enumerate(raw_texts(b.column("text"))):
            lines = t.split(b"\n")
            bad = set(own[i] or ()) if found else known.value
            rest = [x for x in lines if key_hash(x, min_chars) not in bad] if bad else lines
            kept.append(b"\n".join(rest))
            before.append(len(lines))
            gone.append(len(lines) - len(rest))
        done = [pa.array(kept, pa.binary()).cast(pa.string()), pa.array(before, pa.int64()), pa.array(gone, pa.int64())]
        return pa.RecordBatch.from_arrays([*(b.column(c) for c in carry), *done], [*carry, *OUTPUTS])

    return map_text(rows, apply, schema)


def _with_frequent(docs: DataFrame, keys: DataFrame, carry: tuple[str, ...], min_chars: int) -> DataFrame:
    """For key sets too large to broadcast: each row with its own frequent keys, found by a join on the key.

    A text stands for itself by 128 bits of hash, so equal texts are looked up once.
    """

    def explode(b: pa.RecordBatch) -> pa.RecordBatch:
        text, key = [], []
        for t in raw_texts(b.column("text")):
            found = {key_hash(x, min_chars) for x in t.split(b"\n")} - {None}
            text += [xxhash.xxh3_128_digest(t)] * len(found)
            key += found
        return pa.RecordBatch.from_arrays([pa.array(text, pa.binary()), pa.array(key, pa.binary())], ["_of", "key"])

    def mark(b: pa.RecordBatch) -> pa.RecordBatch:
        ids = pa.array([xxhash.xxh3_128_digest(t) for t in raw_texts(b.column("text"))], pa.binary())
        return pa.RecordBatch.from_arrays([*(b.column(c) for c in (*carry, "text")), ids], [*carry, "text", "_of"])

    types = dict(docs.dtypes)
    hits = map_text(docs.select("text"), explode, "_of binary, key binary").distinct().join(keys, "key").groupBy("_of").agg(F.collect_list("key").alias("_frequent"))
    marked = map_text(docs.select(*carry, "text"), mark, ", ".join([*(f"`{c}` {types[c]}" for c in carry), "text string, _of binary"]))
    return marked.join(hits, "_of", "left").drop("_of")
