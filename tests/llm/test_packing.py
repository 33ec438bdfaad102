import random
import zlib

import numpy as np
import public_tokenizers
import pytest
from framedelta.llm import packing as pk
from tokenizers import Tokenizer

PATH = public_tokenizers.path("word_bpe_49k.json")


def test_chunks_encode_like_whole_texts():
    tok, encode = Tokenizer.from_file(PATH), pk.encoder(PATH)
    odd = ["", " ", "Hello, WORLD's   don't\t\nx", "é́é ΣΑΣ ß", "a\x1cb \x85c d   e", "<|endoftext|> x<|startoftext|>y < |endoftext| >", "12 345 ½ 漢字 😀👍🏽 ‍", "İstanbul ǅ", "###*** $$$ |", "x" * 3000]
    odd += ["it's IT'S we'll don't'd ''re,'ve x'", "Straße ÀÉÎõü ÿŸ ×÷ µª º «é» ¿ñ? ¡Ñ!", "a1b22c-3_d%%e&&& ###x***", "~!@#$%^&*()`{}[]|\\:;\"<>?/", "İ ı ſ Å"]
    r = random.Random(3)
    odd += ["".join(r.choice("ab'strevmld AÉßñÿ×÷ª1²,.<|>é ") for _ in range(300)) for _ in range(400)]
    odd += ["".join(r.choice("ab \t\n'é́<|>1😀 \x0b　s") for _ in range(200)) for _ in range(300)]
    for t in odd:
        assert np.frombuffer(encode(t.encode()), "<u4").tolist() == tok.encode(t, add_special_tokens=False).ids, repr(t)


def optimum(items, capacity):
    items = sorted(items, reverse=True)
    best = [len(items)]

    def go(i, bins):
        if len(bins) >= best[0]:
            return
        if i == len(items):
            best[0] = len(bins)
            return
        for room in sorted(set(bins)):
            if room >= items[i]:
                rest = list(bins)
                rest.remove(room)
                go(i + 1, [*rest, room - items[i]])
        go(i + 1, [*bins, capacity - items[i]])

    go(0, [])
    return best[0]


def test_reduction_keeps_the_optimum():
    r = random.Random(5)
    for _ in range(150):
        items = [r.randint(1, 20) for _ in range(r.randint(1, 9))]
        count = {w: items.count(w) for w in set(items)}
        fixed, left = pk.reduce_instance(count, 20)
        rest = [w for w, n in left.items() for _ in range(n)]
        assert sum(n for _, n in fixed) + (optimum(rest, 20) if rest else 0) == optimum(items, 20)
        assert all(sum(w * k for w, k in c) <= 20 for c, _ in fixed)


def test_best_fit_on_runs_is_best_fit():
    r = random.Random(6)
    for _ in range(100):
        items = sorted((r.randint(1, 30) for _ in range(60)), reverse=True)
        bins = []
        for w in items:
            fit = [b for b in bins if b >= w]
            if fit:
                bins.remove(min(fit))
                bins.append(min(fit) - w)
            else:
                bins.append(30 - w)
        got = pk.best_fit({w: items.count(w) for w in set(items)}, 30)
        assert sum(n for _, n in got) == len(bins)


@pytest.mark.parametrize("capacity", [8, 4096])
def test_pack(spark, capacity):
    r = random.Random(4)
    rows = [(i, " ".join("word" for _ in range(r.randint(0, 40))), 1) for i in range(200)] + [(None, None, 2), (7, "dup"), (7, "dup"), (9, "long " * 9000)]
    rows = [(*x[:2], 0, "x") for x in rows]
    df = spark.createDataFrame(rows, "doc_id long, text string, piece int, length string")
    got = pk.pack(df, PATH, capacity).collect()
    tok = Tokenizer.from_file(PATH)
    want = []
    for i, t, *_ in rows:
        ids = [*tok.encode(t or "", add_special_tokens=False).ids, 1]
        for k in range(0, len(ids), capacity):
            part = ids[k : k + capacity]
            want.append((i, k // capacity, k, len(part), zlib.crc32(np.array(part, "<u4").tobytes())))
    assert sorted(map(str, (tuple(x)[:5] for x in got))) == sorted(map(str, want))
    seqs = {}
    for x in got:
        seqs.setdefault(x.sequence_id, []).append((x.offset, x.length))
    for s in seqs.values():
        at = 0
        for off, n in sorted(s):
            assert off == at
            at += n
        assert at <= capacity
    assert len(seqs) <= 1.05 * sum(x.length for x in got) / capacity + 1


def test_empty(spark):
    assert pk.pack(spark.createDataFrame([], "doc_id long, text string"), PATH).count() == 0
