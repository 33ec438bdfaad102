import math
import re

import duckdb
from framedelta.llm import divergence as dv
from framedelta.llm import registry


def brute(text):
    t = text or ""
    w = [x for x in re.split(r"[\x20\x09-\x0D]+", t) if x]
    seen, dup = set(), 0
    for line in t.split("\n"):
        if re.search(r"[^\x20\x09-\x0D]", line):
            dup += line in seen
            seen.add(line)
    at = {}
    for i in range(len(w) - 4):
        at.setdefault(tuple(w[i : i + 5]), []).append(i)
    rep = {i + k for x in at.values() if len(x) > 1 for i in x for k in range(5)}
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), dup, len(rep), len(w) < 10 or 100 * len(rep) > 20 * len(w)


TEXTS = [None, "", " \n\t", "a", "a b c d e a b c d e", "x x x x x x x", "Über é\x0b|#* a\x85b\x00c\n\nÜber\nÜber", "l 1\nl 1\n l 1", "w " * 30_000, "the of and " * 40, " ".join(f"v{i}" for i in range(20_000)), "a b c d e f a b c d e q b c d e f"]


def test_counts(spark):
    rows = [(i % 7 if i else None, t, ["en", None, "de"][i % 3], 1) for i, t in enumerate(TEXTS * 2)]
    df = spark.createDataFrame(rows, "doc_id int, text string, lang string, n_words int")
    got = dv.rate(df, min_reference_docs=1).collect()
    names = ("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")
    want = [(r[0], *brute(r[1])) for r in rows]
    assert sorted((tuple(x[n] for n in names) for x in got), key=str) == sorted(want, key=str)
    assert not any(x.kept and x.base_failed for x in got)
    assert dv.rate(df.limit(0)).count() == 0
    assert all(x.char_divergence is None for x in dv.rate(df, min_reference_docs=1000).collect())


def test_distance(spark):
    from pyspark.sql import functions as F

    p, q = [3, 1, 0], [0.2, 0.3, 0.5]
    m = [(x / 4 + y) / 2 for x, y in zip(p, q, strict=True)]
    kl = lambda a: sum(x * math.log2(x / y) for x, y in zip(a, m, strict=True) if x)
    want = math.sqrt((kl([x / 4 for x in p]) + kl(q)) / 2)
    row = spark.range(1).select(dv.js_distance(F.array(*[F.lit(x).cast("bigint") for x in p]), q).alias("d"), dv.js_distance(F.array(F.lit(0).cast("bigint")), [1.0]).alias("none")).first()
    assert abs(row.d - want) < 1e-12 and row.none is None


def test_oracle(spark, small):
    got = sorted(map(tuple, registry.queries()["op2_divergence"](spark, small).collect()))
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM '{small}/documents.parquet'")
    assert got == sorted(con.sql(registry.oracle_sql()["op2_divergence"]).fetchall())
