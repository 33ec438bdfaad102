"""WARC archives of pages: written, read back, and indexed by an external merge of sorted capture runs.

Writing: a payload is the page's html in UTF-8. Of pages with equal payloads of at least `min_revisit_bytes` the one with
the smallest page_id becomes a response record, the others revisit it. Records go through Spark's text writer, so archives
lie in any file system that Spark writes, are committed as wholes and survive lost executors. Each file is a gzip
stream of WARC/1.1 records.

Reading: files are cut by the JVM where a record can begin and put together again by Content-Length, so a payload
may hold anything, record headers included. Payloads of responses are hashed again and must fit their digest.

Index: captures of an archive, sorted by URL key, timestamp and page_id, are a run. Ranges of the key space gather their part
of each run, and a loser tree merges those k parts. Range by range the result is the capture history of all URLs in order.
A URL with very many captures is cut by timestamp into several ranges.

Defined cases: null html is an empty payload. A page with a null page_id revisits the smallest id with its payload; where all
of them are null, all are responses. Rows which repeat that smallest page_id and payload are responses too. Null and odd URLs are
escaped. Extra columns are ignored. An empty table gives an empty result.
"""

from __future__ import annotations

import base64
import datetime
import hashlib
import re
from collections.abc import Iterator
from urllib.parse import quote, urlsplit

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import map_text, raw_texts, new_path, ship, written

BREAK = b"\r\n\r\nWARC/1.1\r\n"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
EPOCH = datetime.datetime(2024, 1, 1)
#: Digests with several pages are broadcast up to this number of rows; beyond it the pages are shuffled to them.
BROADCAST_DIGESTS = 400_000
#: Captures that one task merges in memory.
MERGED_ROWS = 200_000
CAPTURE = "url_key string, stamp string, page_id bigint, url string, record_type string, payload_bytes bigint, payload_digest string, refers_to bigint, archive string, at bigint, size bigint"


def digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload, usedforsecurity=False).digest()).decode()


def safe_uri(url: str | None) -> str:
    return quote(url or "urn:none", safe=":/?#[]@!$&'()*+,;=%-._~")


def url_key(url: str) -> str:
    """Host parts in reverse, then port, path and query, lower-cased: captures of a site sort together."""
    try:
        u = urlsplit(url)
        host, port = u.hostname or "", u.port
    except ValueError:
        return url.lower()
    if not host:
        return url.lower()
    host = re.sub(r"^www\d*\.", "", host)
    return ",".join(reversed(host.split("."))) + (f":{port}" if port and port not in (80, 443) else "") + ")" + ((u.path or "/") + (f"?{u.query}" if u.query else "")).lower()


def capture_time(page_id: int | None) -> datetime.datetime:
    """Pages hold no time: the id counts seconds from the start of 2024, modulo a century."""
    return EPOCH + datetime.timedelta(seconds=(page_id or 0) % 3_155_760_000)


def record(page_id: int | None, url: str | None, payload: bytes, sha: str, first: int | None) -> bytes:
    """A record with its final line end; a revisit of page `first` if that is given. Without WARC's version line's predecessor."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if first is not None else http + payload
    head = [
        "WARC/1.1",
        f"WARC-Type: {'response' if first is None else 'revisit'}",
        f"WARC-Record-ID: <urn:page:{'none' if page_id is None else page_id}>",
        f"WARC-Date: {capture_time(page_id):%Y-%m-%dT%H:%M:%SZ}",
        f"WARC-Target-URI: {safe_uri(url)}",
        f"WARC-Payload-Digest: sha1:{sha}",
    ]
    if first is not None:
        head += [f"WARC-Refers-To: <urn:page:{first}>", f"WARC-Profile: {PROFILE}"]
    head += ["Content-Type: application/http;msgtype=response", f"Content-Length: {len(block)}", "", ""]
    return "\r\n".join(head).encode() + block + b"\r\n\r\n"


def first_of_payload(pages: DataFrame, min_revisit_bytes: int = 0) -> DataFrame:
    """(payload_digest, first): payloads that several pages have, and the smallest of their ids."""

    def run(b: pa.RecordBatch) -> pa.RecordBatch:
        html = raw_texts(b.column("text"))
        keep = [i for i, x in enumerate(html) if len(x) >= min_revisit_bytes]
        return pa.RecordBatch.from_arrays([b.column("page_id").take(pa.array(keep, pa.int64())), pa.array([digest(html[i]) for i in keep], pa.string())], ["page_id", "payload_digest"])

    rows = map_text(pages.select(F.col("page_id").cast("bigint").alias("page_id"), F.col("html").alias("text")), run, "page_id bigint, payload_digest string")
    return rows.groupBy("payload_digest").agg(F.count(F.lit(1)).alias("n"), F.min("page_id").alias("first")).where("n > 1 and first is not null").select("payload_digest", "first")


def write(pages: DataFrame, path: str, min_revisit_bytes: int = 0) -> None:
    """Write a WARC record for each page into archives under path."""
    several = written(first_of_payload(pages, min_revisit_bytes), "payloads")

    def sums(b: pa.RecordBatch) -> pa.RecordBatch:
        html = raw_texts(b.column("text"))
        # too small payloads get no digest to join by
        return pa.RecordBatch.from_arrays([b.column("page_id"), b.column("url"), b.column("text"), pa.array([digest(x) for x in html], pa.string()), pa.array([len(x) >= min_revisit_bytes for x in html])], ["page_id", "url", "text", "sha", "may"])

    def records(b: pa.RecordBatch) -> pa.RecordBatch:
        out = []
        for i, u, t, sha, first in zip(*(b.column(c).to_pylist() for c in ("page_id", "url")), raw_texts(b.column("text")), *(b.column(c).to_pylist() for c in ("sha", "first")), strict=True):
            out.append(record(i, u, t, sha, None if first is None or first == i else first)[:-1])  # the writer ends each record with the last \n
        return pa.RecordBatch.from_arrays([pa.array(out, pa.binary())], ["value"])

    rows = map_text(pages.select(F.col("page_id").cast("bigint").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").alias("text")), sums, "page_id bigint, url string, text string, sha string, may boolean")
    side = several.withColumnRenamed("payload_digest", "_sha")
    side = F.broadcast(side) if several.count() <= BROADCAST_DIGESTS else side.hint("shuffle_hash")
    rows = rows.join(side, (F.col("sha") == F.col("_sha")) & F.col("may"), "left").select("page_id", "url", "text", "sha", "first")
    done = map_text(rows, records, "value binary")
    done.select(F.col("value").cast("string").alias("value")).write.option("lineSep", "\n").option("compression", "gzip").text(path)


def parse(raw: bytes) -> tuple[dict[str, str], int]:
    """Header fields (lower-case names) of a record without its version line, and where the block begins."""
    end = raw.index(b"\r\n\r\n")
    fields = {}
    for line in raw[:end].decode("utf-8", "replace").split("\r\n"):
        name, _, value = line.partition(":")
        fields[name.strip().lower()] = value.strip()
    return fields, end + 4


def read(spark: SparkSession, path: str) -> DataFrame:
    """A row for each record under path, see CAPTURE; `at` and `size` place it in its unpacked archive."""
    ship(spark)
    parts = spark.read.option("lineSep", BREAK.decode()).text(path).select(F.col("value").cast("binary").alias("value"), F.col("_metadata.file_name").alias("archive"))
    return parts.mapInArrow(_captures, CAPTURE)


def _page_of(urn: str) -> int | None:
    found = re.fullmatch(r"<urn:page:(-?\d+)>", urn)
    return int(found[1]) if found else None


def _captures(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    schema = pa.schema([("url_key", pa.string()), ("stamp", pa.string()), ("page_id", pa.int64()), ("url", pa.string()), ("record_type", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("refers_to", pa.int64()), ("archive", pa.string()), ("at", pa.int64()), ("size", pa.int64())])
    held: list[bytes] = []  # pieces of a record whose block itself holds what looks like a record
    length = need = 0
    now, at = None, 0
    for b in batches:
        rows = []
        for raw, name in zip(b.column("value").to_pylist(), b.column("archive").to_pylist(), strict=True):
            if name != now:
                assert not held, f"{now} ends within a record"
                now, at = name, 0
                raw = raw.removeprefix(BREAK[4:])
            held.append(raw)
            length += len(raw) + (len(BREAK) if len(held) > 1 else 0)
            if length < need:
                continue
            raw = BREAK.join(held)
            fields, begin = parse(raw) if b"\r\n\r\n" in raw else ({}, 0)
            size = int(fields["content-length"]) if fields else 0
            need = begin + size if fields else length + 1
            if length < need:
                held = [raw]
                continue
            held, length, need = [], 0, 0
            block = raw[begin : begin + size]
            assert raw[begin + size :] in (b"", b"\r\n\r\n"), "a record is longer than it says"
            http, http_end = parse(block)
            sha = fields["warc-payload-digest"].removeprefix("sha1:")
            if fields["warc-type"] == "response":
                assert digest(block[http_end:]) == sha, "a payload differs from its digest"
            total = len(BREAK) - 4 + begin + size + 4
            stamp = re.sub(r"\D", "", fields["warc-date"])
            url = fields["warc-target-uri"]
            rows.append((url_key(url), stamp, _page_of(fields["warc-record-id"]), url, fields["warc-type"], int(http["content-length"]), sha, _page_of(fields.get("warc-refers-to", "")), name, at, total))
            at += total
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(x, t.type) for x, t in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)
    assert not held, f"{now} ends within a record"


class LoserTree:
    """Merge of k sorted sequences: inner nodes keep the losers, so each step plays one match a level."""

    def __init__(self, runs: list[list]):
        self.runs = [r for r in runs if r]
        self.k = len(self.runs)
        self.at = [0] * self.k
        self.tree = [-1] * max(1, self.k)
        for i in range(self.k):
            self._play(i, building=True)

    def _beats(self, i: int, j: int) -> bool:
        a, b = (self.runs[x][self.at[x]] if self.at[x] < len(self.runs[x]) else None for x in (i, j))
        return b is None and (a is not None or i < j) or a is not None and b is not None and (a, i) < (b, j)

    def _play(self, winner: int, building: bool = False) -> None:
        node = (winner + self.k) // 2
        while node:
            if self.tree[node] < 0 and building:
                self.tree[node] = winner
                return
            if self._beats(self.tree[node], winner):
                self.tree[node], winner = winner, self.tree[node]
            node //= 2
        self.tree[0] = winner

    def __iter__(self):
        while self.k:
            w = self.tree[0]
            if self.at[w] >= len(self.runs[w]):
                return
            yield self.runs[w][self.at[w]]
            self.at[w] += 1
            self._play(w)


def merged_index(captures: DataFrame, ranges: int | None = None) -> DataFrame:
    """The captures in global order of (url_key, stamp, page_id): partitions are ranges of it, in order, each of them sorted."""
    spark = captures.sparkSession
    ship(spark)
    names = captures.columns
    order = ["url_key", "stamp", "page_id"]
    runs = written(captures.sortWithinPartitions("archive", *order), "runs")
    # so many ranges that a task's part of all runs is small, whatever the table's size
    n = ranges or max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-runs.count() // MERGED_ROWS))
    dealt = runs.repartitionByRange(n, *order).sortWithinPartitions("archive", *order)

    def merge(batches):
        parts = list(batches)
        if not parts:
            return
        t = pa.Table.from_batches(parts).combine_chunks()
        if not t.num_rows:
            return
        cols = [t.column(c).to_pylist() for c in (*order, "archive")]
        runs_here: list[list] = []
        last = None
        for i, (key, stamp, page, run) in enumerate(zip(*cols, strict=True)):
            if run != last:
                runs_here.append([])
                last = run
            runs_here[-1].append((key or "", stamp or "", page is not None, page or 0, i))
        best = pa.array([x[-1] for x in LoserTree(runs_here)], pa.int64())
        yield from t.take(best).to_batches(max_chunksize=10_000)

    types = dict(captures.dtypes)
    return dealt.mapInArrow(merge, ", ".join(f"`{c}` {types[c]}" for c in names))


def archive_and_index(pages: DataFrame, path: str | None = None, min_revisit_bytes: int = 0) -> DataFrame:
    """Write archives of pages under path (in the shared folder by default), read them back and merge the index of their captures."""
    spark = pages.sparkSession
    path = path or new_path(spark, "warc")
    write(pages, path, min_revisit_bytes)
    return merged_index(read(spark, path))
