import random

import numpy as np
from framedelta.llm import decontam_lsa as dl


def corpus():
    r = random.Random(2)
    syll = ["ka", "lo", "mi", "ter", "un", "ves", "dor", "pi", "sha", "gle"]
    word = lambda: "".join(r.choice(syll) for _ in range(r.randint(2, 4)))
    common = ["the", "of", "and", "to", "in"]
    text = lambda n: [r.choice(common) if r.random() < 0.4 else word() for _ in range(n)]
    items = [(i, " ".join(text(r.randint(15, 60)))) for i in range(40)]
    docs, want = [], set()
    for d in range(300):
        w = text(r.randint(5, 400))
        if d % 6 == 0:
            i, p = r.choice(items)
            p = p.split()
            if d % 12 == 0:  # a reworded passage: every sixth word replaced
                p = [word() if k % 6 == 5 else x for k, x in enumerate(p)]
            at = r.randint(0, len(w))
            w = w[:at] + [x.upper() + "," for x in p] + w[at:]
            want.add((d, i))
        docs.append((d, " ".join(w)))
    return docs, items, want


def test_finds_planted_passages(spark):
    docs, items, want = corpus()
    docs += [(None, None), (900, ""), (901, docs[0][1]), (901, docs[0][1]), (902, "the of and " * 20_000)]
    want |= {(901, i) for d, i in want if d == 0}
    df = spark.createDataFrame([(*x, 0) for x in docs], "doc_id long, text string, item_id int")
    bench = spark.createDataFrame([*items, (100, None), (101, "too short")], "item_id long, text string")
    got = dl.leaks(df, bench, background_passages=50)
    assert {(x.doc_id, x.item_id) for x in got.collect()} == want
    assert got.where("doc_id = 901").count() == 2 * len({i for d, i in want if d == 901})
    assert {(x.doc_id, x.item_id) for x in dl.leaks(df, bench, background_passages=50, block_items=15).collect()} == want
    assert dl.leaks(df.limit(0), bench).count() == 0 and dl.leaks(df, bench.limit(0)).count() == 0


def test_common_subsequence():
    r = random.Random(4)
    for _ in range(100):
        a, b = ([r.choice("abcde") for _ in range(r.randint(1, 30))] for _ in range(2))
        best = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                best[i + 1][j + 1] = best[i][j] + 1 if x == y else max(best[i][j + 1], best[i + 1][j])
        vocab = {c: k for k, c in enumerate("abcde")}
        q = dl.Queries([(0, a)], vocab, np.ones(5), np.eye(5), 1.0)
        assert q.common(0, b) == best[-1][-1]


def test_singular_vectors(spark):
    docs, items, _ = corpus()
    vocab = {w: i for i, w in enumerate(dict.fromkeys(x for _, t in items for x in dl.terms(t)))}
    idf = np.linspace(1, 2, len(vocab))
    rows = spark.createDataFrame([(t,) for _, t in items], "text string").repartition(3)
    v = dl.singular_vectors(rows, vocab, idf, 1.0, rank=10, power=8)
    a = np.zeros((len(items), len(vocab)))
    for r, (_, t) in enumerate(items):
        for x in dl.terms(t):
            a[r, vocab[x]] += idf[vocab[x]]
    a /= np.linalg.norm(a, axis=1)[:, None]
    best = np.linalg.svd(a)[1][:10]
    assert np.allclose(np.linalg.norm(a @ v), np.linalg.norm(best), rtol=0.01)


def word_of(r):
    return "".join(r.choice("bcdfghklmnprstvz") + r.choice("aeiou") for _ in range(r.randint(2, 4)))


def test_two_thousand_passages(spark):
    """Far more passages in a block than singular vectors: every verbatim copy is found."""
    r = random.Random(5)
    words = [word_of(r) for _ in range(6000)]
    text = lambda n: [r.choice(words) for _ in range(n)]
    items = [(i, " ".join(text(r.randint(15, 60)))) for i in range(2000)]
    docs = [(i, " ".join([*text(60), *items[i][1].split(), *text(60)])) for i in range(0, 2000, 4)]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    got = dl.leaks(df, spark.createDataFrame(items, "item_id long, text string"), background_passages=50).collect()
    assert {(x.doc_id, x.item_id) for x in got} == {(i, i) for i, _ in docs}


def test_frequent_short_and_long_passages(spark):
    """Copies of passages which a third of the documents hold, of 5 to 7 and of 1000 words."""
    r = random.Random(6)
    words = [word_of(r) for _ in range(3000)]
    text = lambda n: [r.choice(words) for _ in range(n)]
    items = [(i, " ".join(text(n))) for i, n in enumerate([18, 46, 5, 6, 7, 5, 6, 7, 1000, 400])] + [(100 + i, " ".join(text(40))) for i in range(40)]
    docs, want = [], set()
    for d in range(360):
        w = text(r.randint(30, 300))
        for i, often in [(0, 3), (1, 3), *((k, 20) for k in range(2, 10))]:
            if (d + i) % often == 0:
                at = r.randint(0, len(w))
                w = w[:at] + items[i][1].split() + w[at:] if i < 2 else w + text(30) + items[i][1].split() + text(30)
                want.add((d, i))
        docs.append((d, w))
    has = lambda w, p: any(w[k : k + len(p)] == p for k in range(len(w)))
    want = {(d, i) for d, i in want if has(docs[d][1], items[i][1].split())}  # a later copy may cut an earlier one
    df = spark.createDataFrame([(d, " ".join(w)) for d, w in docs], "doc_id long, text string")
    got = {(x.doc_id, x.item_id) for x in dl.leaks(df, spark.createDataFrame(items, "item_id long, text string"), background_passages=50).collect()}
    assert want <= got and all(i < 2 for _, i in got - want)


def test_passage_in_a_third_of_documents_among_rare_words(spark):
    """Most benchmark words are rare, so words outside it weigh far more than those of a passage which many documents hold."""
    r = random.Random(8)
    text = lambda n: [word_of(r) for _ in range(n)]
    items = [(i, " ".join(text(n))) for i, n in enumerate([18, 46] + [40] * 60)]
    docs = [(d, " ".join([*text(r.randint(30, 80)), *(items[d % 6 // 3][1].split() if d % 3 == 0 else []), *text(40)])) for d in range(900)]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    got = dl.leaks(df, spark.createDataFrame(items, "item_id long, text string"), background_passages=50).collect()
    assert {(x.doc_id, x.item_id) for x in got} == {(d, d % 6 // 3) for d in range(0, 900, 3)}


def test_short_passages_follow_each_other(spark):
    docs = [(1, "alpha, beta gamma"), (2, "beta alpha gamma"), (3, "Alpha beta\ngamma delta"), (4, "alpha betagamma"), (5, "solo"), (6, "")]
    items = [(1, "alpha beta gamma"), (2, "Solo"), (3, "..."), (4, None)]
    df, bench = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    assert {(x.doc_id, x.item_id) for x in dl.leaks(df, bench, background_passages=20).collect()} == {(1, 1), (3, 1), (5, 2)}


def test_a_passage_of_1500_words(spark):
    r = random.Random(6)
    long = " ".join(f"p{r.randint(0, 900)}" for _ in range(1500))
    text = lambda n: " ".join(f"w{r.randint(0, 5000)}" for _ in range(n))
    docs = [(i, text(300) + (" " + long + " " if i % 2 else " ") + text(300)) for i in range(20)]
    df, bench = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame([(1, long)], "item_id long, text string")
    assert {x.doc_id for x in dl.leaks(df, bench, background_passages=20).collect()} == set(range(1, 20, 2))


def test_words_of_any_text():
    for t in ("a\xa0b\x85c_ª²½ ÀÉ ß µ", "Ωμέγα x", "", "İstanbul", "ÿÿ 12-3"):
        assert dl.terms(t) == dl.TERM.findall(t.lower())
