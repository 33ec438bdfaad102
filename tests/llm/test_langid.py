from framedelta.llm import langid_crf as lc
from framedelta.llm import registry
from pyspark.sql import functions as F


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    out = registry.queries()["op1_language_crf"](spark, sf)
    assert out.count() == docs.count()
    x = out.where("held_out").join(docs.select("doc_id", "lang"), "doc_id")
    right = x.agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("double"))).first()[0]
    assert right > 0.98
    assert x.where("score < 0 or score > 1").count() == 0


def test_cases(spark):
    rows = [(1, "the and of that with", "en"), (2, "der die und schön", "de"), (3, None, "en"), (4, "", None), (None, "123 !!\n", "de"), (2, "der die und schön", "de"), (7, "the of " * 30_000, "en")]
    df = spark.createDataFrame([(*r, 0.5) for r in rows], "doc_id long, text string, lang string, score double")
    m = lc.fitted(df, F.lit(True))
    got = sorted(((x.doc_id, x.lang_pred, round(x.score, 2) > 0.5) for x in lc.predict(df, m).collect()), key=str)
    assert got == sorted([(1, "en", True), (2, "de", True), (3, "und", False), (4, "und", False), (None, "und", False), (2, "de", True), (7, "en", True)], key=str)
    none = lc.fitted(df.where("lang is null"), F.lit(True))
    assert none is None and {x.lang_pred for x in lc.predict(df, none).collect()} == {"und"}
    assert lc.predict(df.limit(0), m).count() == 0


def test_code_switch():
    import random

    r = random.Random(1)
    en, de = ["the", "and", "ing", "that", "with", "thing"], ["der", "die", "und", "schen", "keit", "lich"]
    sample = [(" ".join(r.choice(w) for _ in range(20)), y) for w, y in ((en, "en"), (de, "de")) for _ in range(40)]
    m = lc.learn(sample)
    got = [y for _, y, _ in lc.word_labels("the that thing und der schen lich and with", m)]
    assert got == ["en"] * 3 + ["de"] * 4 + ["en"] * 2


def test_letters_alone_make_words(spark):
    assert lc.words_of("x²y ½ ⅷ 12_a é-ß") == ["x", "y", "a", "é", "ß"]
    df = spark.createDataFrame([(1, "² ½ Ⅷ 123", None), (2, "the the of", "en"), (3, "der das und", "de")], "doc_id long, text string, lang string")
    got = {x.doc_id: (x.lang_pred, x.score) for x in lc.predict(df, lc.fitted(df, F.lit(True))).collect()}
    assert got[1] == ("und", 0.0)


def test_a_tie_goes_to_the_first_language(spark):
    df = spark.createDataFrame([(1, "zz zz zz zz", "b"), (2, "zz zz zz zz", "a"), (3, "zz", None)], "doc_id long, text string, lang string")
    got = lc.predict(df, lc.fitted(df, F.lit(True))).collect()
    assert all(abs(x.score - 0.5) < 0.02 for x in got)
    m = lc.learn([("zz", "b"), ("zz", "a")])
    m.weights[:], m.transitions[:] = 0, 0
    assert {x.lang_pred for x in lc.predict(df, m).collect()} == {"a"}


def test_every_language_is_learned(spark):
    langs = [f"l{chr(97 + i // 26)}{chr(97 + i % 26)}" for i in range(80)]
    words = {y: [f"{y[1:]}{c}{y[1:]}" for c in "pqrs"] for y in langs}
    df = spark.createDataFrame([(i, " ".join(words[y]) + "\n" + " ".join(reversed(words[y])), y) for i, y in enumerate(langs)], "doc_id long, text string, lang string")
    m = lc.fitted(df, F.lit(True))
    assert m.langs == langs
    right = [x.doc_id for x in lc.predict(df, m).collect() if x.lang_pred == langs[x.doc_id]]
    assert len(right) >= 78


def test_keys_of_features_are_distinct():
    import numpy as np

    words = ["abc", "cba", "a", "ab", "wörter", "straße"]
    bi, tri, first, ends = lc.feature_keys(words)
    assert (bi != 0).sum() == sum(len(w) + 1 for w in words) and (tri != 0).sum() == sum(len(w) for w in words)
    assert ends[2].tolist() == [0, 0] and ends[0, 0] != ends[0, 1] and ends[0, 0] != ends[1, 1]
    keys = np.unique(np.concatenate([bi, tri, ends.ravel()]))[1:]
    table = lc.KeyTable(keys)
    assert table.get(keys).tolist() == list(range(len(keys)))
    assert (table.get(np.array([0, 5, 2**63 + 9], np.uint64)) == len(keys)).all()


def test_whole_query_against_a_plain_one(spark, small):
    """Each text again, alone and word by word, by the recursion over all label sequences of short lines and forward-backward in plain Python."""
    import math

    docs = spark.read.parquet(f"{small}/documents.parquet").limit(60)
    m = lc.fitted(spark.read.parquet(f"{small}/documents.parquet"), F.lit(True))
    k = len(m.langs)
    for x, r in zip(sorted(lc.predict(docs, m).collect(), key=lambda x: x.doc_id), sorted(docs.collect(), key=lambda x: x.doc_id), strict=True):
        total = [0.0] * k
        for line in lc.text_lines(r.text or ""):
            e = [[math.exp(float(v)) for v in row] for row in m.rows(line)]
            t = [[math.exp(float(v)) for v in row] for row in m.transitions]
            a = [e[0]]
            for o in e[1:]:
                a.append([o[j] * sum(a[-1][i] * t[i][j] for i in range(k)) for j in range(k)])
                s = sum(a[-1])
                a[-1] = [v / s for v in a[-1]]
            b = [[1.0] * k]
            for o in reversed(e[1:]):
                b.append([sum(t[i][j] * o[j] * b[-1][j] for j in range(k)) for i in range(k)])
                s = sum(b[-1])
                b[-1] = [v / s for v in b[-1]]
            for w, p, q in zip(line, a, reversed(b), strict=True):
                z = sum(u * v for u, v in zip(p, q, strict=True))
                for j in range(k):
                    total[j] += len(w) * p[j] * q[j] / z
        if sum(total):
            assert abs(max(total) / sum(total) - x.score) < 1e-3
            assert x.lang_pred == m.langs[total.index(max(total))] or sorted(total)[-1] - sorted(total)[-2] < 1e-3 * sum(total)
        else:
            assert x.lang_pred == "und"
