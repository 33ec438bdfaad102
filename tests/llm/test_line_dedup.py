import collections
import hashlib

import pytest
from framedelta.llm import line_dedup as ld

SPACE = " \t\n\v\f\r"
ROWS = [(i, "common line\nown %d" % i) for i in range(12)] + [(None, None), (20, ""), (20, ""), (21, "  COMMON line\t\nÉ\n\n"), (22, "é"), (23, "x " * 50_000 + "\ncommon line")]


def brute(rows, min_docs=10, min_chars=1):
    low = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    key = lambda x: x.strip(SPACE).translate(low)
    n = collections.Counter(k for _, t in rows for k in {key(x) for x in (t or "").split("\n")})
    out = []
    for i, t in rows:
        lines = (t or "").split("\n")
        kept = [x for x in lines if not (len(key(x)) >= min_chars and n[key(x)] >= min_docs)]
        out.append((i, "\n".join(kept), len(lines), len(lines) - len(kept)))
    return sorted(out, key=str)


@pytest.mark.parametrize("most", [1000, 0])
def test_brute_force(spark, most):
    df = spark.createDataFrame([(*r, 1, "clash") for r in ROWS], "doc_id long, text string, n_lines int, key string")
    got = ld.drop_frequent_lines(df, broadcast_keys=most, carry=("doc_id", "n_lines")).select("doc_id", "text", "n_lines", "n_dropped")
    assert sorted(map(tuple, got.collect()), key=str) == brute(ROWS)


def test_longer_keys_only(spark):
    rows = [(i, "é\nab\nabc") for i in range(3)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = ld.drop_frequent_lines(df, min_docs=3, min_chars=2).collect()
    assert [r.text for r in got] == ["é"] * 3


def test_empty(spark):
    df = spark.createDataFrame([], "doc_id long, text string")
    assert ld.drop_frequent_lines(df).count() == 0


def test_hash_of_null_text(spark):
    from pyspark.sql import functions as F

    df = spark.createDataFrame([(1, None)], "doc_id long, text string")
    assert ld.drop_frequent_lines(df).select(F.sha2("text", 256)).first()[0] == hashlib.sha256(b"").hexdigest()
