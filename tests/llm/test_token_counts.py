import random

import public_tokenizers
from framedelta.llm import token_counts as tc

PATH = public_tokenizers.path("piece_bpe_32k.model")


def greedy(word, begin, go_on):
    at, n = 0, 0
    while at < len(word):
        pieces = go_on if at else begin
        end = next((e for e in range(len(word), at, -1) if word[at:e] in pieces), None)
        if end is None:
            return 0
        at, n = end, n + 1
    return n


def test_small_vocabularies():
    r = random.Random(1)
    for _ in range(200):
        begin, go_on = ({"".join(r.choice("abc") for _ in range(r.randint(1, 5))) for _ in range(r.randint(0, 9))} for _ in range(2))
        a = tc.Automaton(begin, go_on)
        for _ in range(60):
            w = "".join(r.choice("abcd" if r.random() < 0.1 else "abc") for _ in range(r.randint(1, 12)))
            assert a.count(w) == greedy(w, begin, go_on), (w, begin, go_on)


def test_real_vocabulary(spark, small):
    begin, go_on = tc.vocabulary(PATH)
    rows = [(x.doc_id, x.text) for x in spark.read.parquet(f"{small}/documents.parquet").limit(40).collect()]
    rows += [(None, None), (1000, ""), (1001, "漢字 😀 a\x0bb"), (1001, "漢字 😀 a\x0bb"), (1002, "word " * 50_000)]
    df = spark.createDataFrame([(*x, 1) for x in rows], "doc_id long, text string, n_words int")
    want = []
    for i, t in rows:
        n = [greedy(w.decode(), begin, go_on) for w in (t or "").encode().split()]
        want.append((i, len(n), sum(n) + n.count(0), n.count(0)))
    assert sorted(map(tuple, tc.count_tokens(df, PATH).collect()), key=str) == sorted(want, key=str)
    assert tc.count_tokens(df.limit(0), PATH).count() == 0
