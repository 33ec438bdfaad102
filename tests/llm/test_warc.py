import gzip
import glob
import heapq
import random

import duckdb
from framedelta.llm import registry
from framedelta.llm import warc_index as wi

SEP = "\r\n\r\nWARC/1.1\r\nWARC-Type: response\r\n\r\n"


def test_loser_tree():
    r = random.Random(1)
    for k in (0, 1, 2, 3, 5, 8, 13):
        runs = [sorted(r.randint(0, 50) for _ in range(r.randint(0, 30))) for _ in range(k)]
        assert list(wi.LoserTree(runs)) == list(heapq.merge(*runs))


ROWS = [
    (5, "http://a.com/x", "<p>é</p>"),
    (3, "https://www.a.com/x", "<p>é</p>"),
    (9, "http://b.org:8080/Q?z=1", "<p>é</p>"),
    (None, None, "<p>é</p>"),
    (1, "http://a.com/y z\r\nX: 1", None),
    (2, "", ""),
    (7, "http://c.com", SEP + "tail" + SEP),
    (8, "http://c.com", SEP),
    (8, "http://c.com", SEP),
    (10, "http://c.com", "line\r\n\r\n\r\n\r\nWARC/1.1\r\r\n\r\nWARC/1.1\r\n"),
    (11, "http://d.com", "x" * 300_000),
    (12, "http://[bad", "\r\n\r"),
]


def test_round_trip(spark, tmp_path):
    df = spark.createDataFrame([(*x, "s", 1) for x in ROWS], "page_id long, url string, html string, text string, first int")
    got = wi.archive_and_index(df, f"file://{tmp_path}/w").collect()
    first = {}
    for i, _, h in ROWS:
        first[h or ""] = min(x for x in (first.get(h or ""), i) if x is not None)
    want = [(i, len((h or "").encode()), wi.digest((h or "").encode()), "response" if first[h or ""] == i else "revisit", None if first[h or ""] == i else first[h or ""]) for i, _, h in ROWS]
    assert sorted(((x.page_id, x.payload_bytes, x.payload_digest, x.record_type, x.refers_to) for x in got), key=str) == sorted(want, key=str)
    keys = [(x.url_key, x.stamp, x.page_id is not None, x.page_id or 0) for x in got]
    assert keys == sorted(keys)
    for f in glob.glob(f"{tmp_path}/w/*.gz"):
        whole = gzip.open(f).read()
        for x in got:
            if f.endswith(x.archive):
                part = whole[x.at : x.at + x["size"]]
                assert part.startswith(b"WARC/1.1\r\n") and part.endswith(b"\r\n\r\n")
                assert b"<urn:page:%s>" % str("none" if x.page_id is None else x.page_id).encode() in part.split(b"\r\n\r\n")[0]
    assert wi.archive_and_index(df.limit(0)).count() == 0


def test_shuffled_decisions_and_minimum(spark, monkeypatch):
    monkeypatch.setattr(wi, "BROADCAST_DIGESTS", 0)
    df = spark.createDataFrame(ROWS, "page_id long, url string, html string")
    got = {(x.page_id, x.record_type) for x in wi.archive_and_index(df, min_revisit_bytes=8).collect()}
    assert (2, "response") in got and (1, "response") in got and (5, "revisit") in got and (3, "response") in got


def test_oracle(spark, small):
    got = sorted(map(tuple, registry.queries()["op8_warc_index"](spark, small).collect()))
    con = duckdb.connect()
    con.sql(f"CREATE VIEW pages AS SELECT * FROM '{small}/pages.parquet'")
    rel = con.sql(registry.oracle_sql()["op8_warc_index"])
    assert got == sorted(rel.fetchall())
