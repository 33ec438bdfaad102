import numpy as np
from framedelta.llm import quality_crf as qc
from framedelta.llm import registry
from pyspark.sql import functions as F


def test_features_by_hand():
    x, size, n = qc.line_features([b"Ab c! *** c c\n\nzz", b"", "é 12|".encode(), b"z\nz\nz"])
    assert size.tolist() == [13, 0, 2, 0, 6, 1, 1, 1] and n.tolist() == [3, 1, 1, 3]
    space, lower, upper, digit, mark, symbol, beyond, _ = (x[:, :8] * np.maximum(size, 1)[:, None]).T
    assert space.tolist() == [4, 0, 0, 0, 1, 0, 0, 0] and lower.tolist() == [4, 0, 2, 0, 0, 1, 1, 1] and upper[0] == 1
    assert digit[4] == 2 and beyond[4] == 2 and symbol.tolist() == [4, 0, 0, 0, 1, 0, 0, 0] and mark.sum() == 0
    assert np.allclose(np.expm1(x[:, 9]), [5, 0, 1, 0, 2, 1, 1, 1])
    assert np.isclose(x[0, 11], 1 / 5)  # c c
    assert x[:, -2].tolist() == [0, 0, 0, 0, 0, 0, 1, 1]
    assert np.isclose(x[0, -3], 5 / 6) and np.isclose(x[7, -3], 1 / 3) and x[3, -3] == 0


def test_held_out(spark):
    sf = "/root/testdata/sf0.01"
    out = registry.queries()["op7_quality_crf"](spark, sf)
    x = out.where("held_out").join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id")
    r = x.agg(F.avg((F.col("predicted") == F.col("quality")).cast("double")).alias("acc"), F.min("score").alias("lo"), F.max("score").alias("hi")).first()
    assert r.acc > 0.95 and r.lo >= 0 and r.hi <= 1
    assert out.count() == 1000 and out.where("(score >= 0.3) <> (predicted = 1)").count() == 0


def test_cases(spark):
    rows = [(i, "good words in a line.\nmore of them here.", 1) for i in range(10)] + [(i, "### *** BAD!!\n$$$ XX", 0) for i in range(10, 20)]
    rows += [(None, None, None), (30, "", None), (30, "", None), (31, "x " * 60_000, None)]
    df = spark.createDataFrame([(a, b, 9.0) for a, b, _ in rows], "doc_id long, text string, score double")
    labels = spark.createDataFrame([(a, c) for a, _, c in rows], "doc_id long, quality int")
    m = qc.fitted(df, labels, F.lit(True))
    got = qc.predict(df, m).collect()
    assert len(got) == len(rows) and all(0 <= x.score <= 1 for x in got)
    assert all(x.predicted == 1 for x in got if x.doc_id is not None and x.doc_id < 10) and all(x.predicted == 0 for x in got if x.doc_id is not None and 10 <= x.doc_id < 20)
    none = qc.fitted(df, labels.limit(0), F.lit(True))
    assert {x.score for x in qc.predict(df, none).collect()} == {0.5}
    assert qc.predict(df.limit(0), m).count() == 0
