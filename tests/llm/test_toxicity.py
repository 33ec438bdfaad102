import itertools

import numpy as np
from framedelta.llm import registry
from framedelta.llm import toxicity_ws as tw
from pyspark.sql import functions as F


def test_patterns():
    p = tw.Patterns(["abc*", "abc", "réeux*", "pig"])
    assert p.counts("ABC abcd xabc pigs PIG. Réeuxment abc") == {0: 3, 1: 2, 2: 1, 3: 1}
    assert tw.Patterns([]).counts("abc") == {} and p.counts("") == {}


def test_label_model_finds_accuracies_and_correlations():
    r = np.random.default_rng(3)
    n = 4000
    y = r.random(n) < 0.3
    cols = [np.where(r.random(n) < acc, y, ~y).astype(int) for acc in (0.9, 0.8, 0.85, 0.75)]
    cols.append(np.where(r.random(n) < 0.97, cols[3], 1 - cols[3]))  # a copy of the worst voter
    votes = np.column_stack(cols)
    m = tw.LabelModel(prior=0.3)
    q = m.fit(votes, np.full(n, -1))
    assert (3, 4) in {tuple(sorted((j, p))) for j, p in enumerate(m.parent) if p >= 0}
    assert ((q > 0.5) == y).mean() > 0.9
    acc = [(m.table[j][1, :, 2] * 1).mean() for j in range(3) if m.parent[j] < 0]
    assert all(a > 0.6 for a in acc)


def test_posterior_equals_bayes():
    votes = np.array(list(itertools.product((-1, 0, 1), repeat=2)))
    m = tw.LabelModel(prior=0.2)
    m.parent = [-1, 0]
    r = np.random.default_rng(1)
    m.table = [t / t.sum(2, keepdims=True) for t in r.random((2, 2, 3, 3))]
    m.table[0][:, 1:] = m.table[0][:, :1]
    got = m.posterior(votes)
    for (a, b), g in zip(votes, got, strict=True):
        w = [p * m.table[0][y, 0, a + 1] * m.table[1][y, a + 1, b + 1] for y, p in ((0, 0.8), (1, 0.2))]
        assert np.isclose(g, w[1] / sum(w))


def test_held_out(spark):
    sf = "/root/testdata/sf0.1"
    out = registry.queries()["op4_toxicity"](spark, sf)
    x = out.where("held_out").join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id")
    r = x.agg(F.avg((F.col("predicted") == F.col("toxic")).cast("double")).alias("acc"), F.avg(F.when(F.col("toxic") == 1, F.col("predicted"))).alias("recall")).first()
    assert r.acc > 0.97 and r.recall > 0.85


def test_cases(spark):
    rows = [(i, f"you idiot {i} moron trash", 1) for i in range(30)] + [(i, f"nice calm words {i}", 0) for i in range(30, 90)] + [(None, None, None), (91, "", None), (91, "", None), (92, "fine " * 50_000 + "idiot", None)]
    df = spark.createDataFrame([(a, b, 9) for a, b, _ in rows], "doc_id long, text string, score int")
    labels = spark.createDataFrame([(a, c) for a, _, c in rows], "doc_id long, toxic int")
    for known in (labels, labels.limit(0)):
        m = tw.fitted(df, known, F.lit(True), unlabelled=100)
        got = tw.predict(df, m).collect()
        assert len(got) == len(rows) and all(0 <= x.score <= 1 for x in got)
        assert all(x.predicted == 1 for x in got if x.doc_id is not None and x.doc_id < 30)
        assert all(x.predicted == 0 for x in got if x.doc_id is None or 30 <= x.doc_id < 92)
    assert tw.predict(df.limit(0), m).count() == 0
    tw.fitted(df.limit(0), labels, F.lit(True))


def test_both_labels_above_the_sample(spark):
    """A table whose labels are rarer than the sample's: shares are the table's, not the sample's."""
    r = np.random.default_rng(2)
    common = [f"{a}{b}" for a in ("path", "lost", "stup", "wort", "gar", "trans") for b in ("way", "ing", "er", "on", "ly", "en")]
    rows = []
    for i in range(6000):
        bad = i % 12 == 0
        words = r.choice(common, 40).tolist()
        if bad:
            words[int(r.integers(40))] = str(r.choice(["grobzan", "grobzil", "stupid"]))
        rows.append((i, " ".join(words), int(bad)))
    df = spark.createDataFrame(rows, "doc_id long, text string, toxic int")
    m = tw.fitted(df.select("doc_id", "text"), df.select("doc_id", "toxic"), F.col("doc_id") % 5 != 0, per_label=150, unlabelled=200)
    x = tw.predict(df.where("doc_id % 5 = 0"), m).join(df.select("doc_id", "toxic"), "doc_id")
    r = x.agg(F.avg(F.when(F.col("toxic") == 1, F.col("predicted"))).alias("recall"), F.avg(F.when(F.col("toxic") == 0, 1 - F.col("predicted"))).alias("clean")).first()
    assert r.recall >= 0.9 and r.clean >= 0.97


def test_telling_patterns():
    sample = [("pathway lost words", 0, 3.0)] * 30 + [("pathetic lost words", 1, 0.5)] * 20 + [("zorkly zorkan", 1, 0.5)] * 10 + [("zorkul", 1, 0.5)] * 10
    assert tw.telling(sample) == ["pathetic", "zork*"]


def test_scores_against_a_plain_sum(spark):
    """Each text again from its own words: counts by comparing words, the sum by hand."""
    import math
    import re

    df = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    m = tw.fitted(df, spark.read.parquet("/root/testdata/sf0.001/labels.parquet"), F.lit(True))
    names = m.pats.names
    for x in tw.predict(df.limit(80), m, carry=("doc_id", "text")).collect():
        runs = [w for w in "".join(c if c.isalpha() else " " for c in (x.text or "").lower()).split()]
        k = [sum(w.startswith(n[:-1]) if n.endswith("*") else w == n for w in runs) for n in names]
        n, hits = len((x.text or "").split()), sum(k)
        caps = sum(w.isupper() and len(w) > 2 for w in (x.text or "").split())
        rest = [math.log1p(hits), hits >= 2, sum(v > 0 for v in k) >= 2, math.log1p(1000 * hits / max(n, 1)), bool(hits) and bool(re.search(tw.YOU, (x.text or "").lower())), caps / max(n, 1), (x.text or "").count("!") > 3]
        z = sum(a * b for a, b in zip([math.log1p(v) for v in k] + [float(v) for v in rest], m.weights[:-1], strict=True)) + m.weights[-1]
        assert abs(1 / (1 + math.exp(-max(-30, min(30, z)))) - x.score) < 1e-6
