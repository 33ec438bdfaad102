import random

import numpy as np
from framedelta.llm import simhash_text as st
from pyspark.sql import functions as F


def shingles(t, width=5):
    w = (t or "").lower().split()
    return {tuple(w[i : i + width]) for i in range(max(1, len(w) - width + 1))} if w else set()


def brute(rows, least=0.8):
    sets = [shingles(t) for _, t in rows]
    label = list(range(len(rows)))
    for i in range(len(rows)):
        for j in range(i):
            a, b = sets[i], sets[j]
            if (not a and not b) or (a and b and len(a & b) >= least * len(a | b)):
                old, new = max(label[i], label[j]), min(label[i], label[j])
                label = [new if x == old else x for x in label]
    return label


def made(seed=3, bases=12, copies=14):
    r = random.Random(seed)
    word = lambda: f"w{r.randint(0, 10**6)}"
    rows, n = [], 0
    for _ in range(bases):
        t = [word() for _ in range(r.randint(60, 250))]
        for _ in range(copies):
            x = list(t)
            for _ in range(r.randint(0, 6)):
                x[r.randrange(len(x))] = word()
            rows.append((n, " ".join(x)))
            n += 1
    return rows + [(n, None), (n + 1, ""), (n + 2, " \n"), (n + 3, "two words"), (n + 4, "Two  WORDS"), (n + 5, "y " * 30_000)]


def test_classes_equal_brute_force(spark):
    rows = made()
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    want = brute(rows)
    for hot, recall in ((512, 0.98), (4, 0.9)):  # shards in one task, and shards taken apart by leaders
        of_row, of_text = st.similar_classes(df, hot=hot)
        got = {x.doc_id: bytes(x["class"]) for x in of_row.join(of_text, "tid").collect()}
        pairs = {(i, j) for i in range(len(rows)) for j in range(i) if want[i] == want[j]}
        found = {(i, j) for i in range(len(rows)) for j in range(i) if got[i] == got[j]}
        assert not found - pairs
        assert len(found) >= recall * len(pairs), hot


def test_one_row_of_each_class_stays(spark):
    rows = [(None, "a b c d e f g"), (5, "A b c d  e f g"), (5, "A b c d  e f g"), (None, "only here without an id"), (None, "only here without an id"), (7, None), (8, ""), (9, "first text of nine"), (9, "second text of nine")]
    df = spark.createDataFrame([(*x, i, 0.5) for i, x in enumerate(rows)], "doc_id long, text string, tid int, bands double")
    got = st.one_of_each(df)
    assert got.dtypes == df.dtypes
    assert sorted((x.doc_id is None, x.doc_id) for x in got.collect()) == [(False, 5), (False, 7), (False, 9), (False, 9), (True, None)]
    assert st.one_of_each(df.limit(0)).count() == 0


def test_a_large_star(spark):
    r = random.Random(1)
    base = [f"w{i}" for i in range(300)]
    rows = []
    for i in range(1500):
        x = list(base)
        x[r.randrange(300)] = f"z{i}"
        rows.append((i, " ".join(x)))
    got = st.one_of_each(spark.createDataFrame(rows, "doc_id long, text string").repartition(4))
    assert [x.doc_id for x in got.collect()] == [0]


def test_sketch():
    h = st.shingle_hashes(st.words(b"a b c d e f a b c d e"))
    assert len(h) == 7 and h[0] == h[6] and len(st.shingle_hashes([b"x"])) == 1 and st.sketch(st.shingle_hashes([])) == (0, [])
    r = np.random.default_rng(0)
    x = r.integers(0, 1 << 63, 20_000).astype(np.uint64)
    y = x.copy()
    y[:2200] = r.integers(0, 1 << 63, 2200).astype(np.uint64)  # a similarity of about 0.8
    (f, a), (g, b) = st.sketch(x), st.sketch(y)
    assert sum(p == q for p, q in zip(a, b, strict=True)) >= 1 and ((f ^ g) & ((1 << 64) - 1)).bit_count() <= 18


def test_recall_on_documents(spark):
    """Against brute force over all pairs that share a shingle, on a whole table."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    rows = [(x.doc_id, x.text) for x in docs.collect()]
    want = brute(rows)
    of_row, of_text = st.similar_classes(docs)
    got = {x.doc_id: bytes(x["class"]) for x in of_row.join(of_text, "tid").collect()}
    ids = [i for i, _ in rows]
    pairs = {(i, j) for i in range(len(ids)) for j in range(i) if want[i] == want[j]}
    found = {(i, j) for i in range(len(ids)) for j in range(i) if got[ids[i]] == got[ids[j]]}
    assert not found - pairs and len(found) >= 0.9 * len(pairs)
    assert of_text.agg(F.count_distinct("class")).first()[0] >= len(set(want))


def test_every_pair_of_a_shard_is_looked_at(spark):
    """A text whose nearest in its shards, on both sides, are no partners of it, and which has one that is farther."""
    rows = made(seed=8, bases=40, copies=12)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    sets = {i: shingles(t) for i, t in rows}
    sk = {i: st.sketch(st.shingle_hashes(st.words((t or "").encode()))) for i, t in rows}
    want = list(range(len(rows)))
    for i in range(len(rows)):
        for j in range(i):
            a, b = sets[i], sets[j]
            met = set(sk[i][1]) & set(sk[j][1]) and ((sk[i][0] ^ sk[j][0]) & ((1 << 64) - 1)).bit_count() <= 18
            same = st.words((rows[i][1] or "").encode()) == st.words((rows[j][1] or "").encode())
            if same or (met and len(a & b) >= 0.8 * len(a | b)):
                old, new = max(want[i], want[j]), min(want[i], want[j])
                want = [new if x == old else x for x in want]
    pairs = {(i, j) for i in range(len(rows)) for j in range(i) if want[i] == want[j]}
    for hot in (512, 4):
        of_row, of_text = st.similar_classes(df, hot=hot)
        got = {x.doc_id: bytes(x["class"]) for x in of_row.join(of_text, "tid").collect()}
        assert {(i, j) for i in range(len(rows)) for j in range(i) if got[i] == got[j]} == pairs, hot
