import random

import xxhash
from framedelta.llm import simhash as sh


def slow_fingerprint(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    for c in "\t\n\v\f\r":
        low = low.replace(c, " ")
    w = [x for x in low.split(" ") if x]
    if not w:
        return 0
    s = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or [" ".join(w)]
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def classes(codes, radius):
    root = list(range(len(codes)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(codes)):
        for j in range(i):
            if (codes[i] ^ codes[j]).bit_count() <= radius:
                root[max(find(i), find(j))] = min(find(i), find(j))
    return [find(i) for i in range(len(codes))]


def flipped(x, n, r):
    for b in r.sample(range(64), n):
        x ^= 1 << b
    return x


def test_fingerprint():
    for t in ["", " \n", "one", "One TWO", "a b c", "É a\x0bb c d É x", "w " * 5000, "a b c a b c a b c"]:
        assert sh.fingerprint(t.encode()) == slow_fingerprint(t)


def test_masks_lose_no_pair():
    r = random.Random(1)
    for n in (10, 10**8, 10**10):
        masks = sh.plan_masks(n, 3)
        for _ in range(300):
            x = r.getrandbits(64)
            y = flipped(x, 3, r)
            assert any(x & m == y & m for m in masks)


def test_links_connect_what_brute_force_connects(spark):
    r = random.Random(2)
    codes = [r.getrandbits(64) for _ in range(200)]
    codes += [flipped(c, r.randint(1, 4), r) for c in codes[:150]]
    center = r.getrandbits(64)
    codes += [flipped(center, r.randint(1, 5), r) for _ in range(300)]
    codes = list(dict.fromkeys(codes))
    want = classes(codes, 3)
    df = spark.createDataFrame([(sh._signed(c),) for c in codes], "fp long")
    for hot in (1000, 20):
        label = {x.v: x.label for x in sh.components(sh.near_links(df, 3, hot)).collect()}
        got = [label.get(sh._signed(c), sh._signed(c)) for c in codes]
        pairs = set(zip(want, got, strict=True))
        assert len(pairs) == len(set(want)) == len(set(got))


def test_rows(spark):
    long = " ".join(f"word{i}" for i in range(3000))
    rows = [(5, long), (3, long + " end"), (None, long), (9, None), (8, ""), (8, ""), (7, "other words here now")]
    df = spark.createDataFrame([(*x, 0) for x in rows], "doc_id long, text string, fp int")
    got = {(x.doc_id, x.fingerprint, x.component_id) for x in sh.near_duplicates(df).collect()}
    fp = {t: f"{slow_fingerprint(t):016x}" for _, t in rows}
    assert got == {(5, fp[long], 3), (3, fp[long + " end"], 3), (None, fp[long], 3), (9, "0" * 16, 8), (8, "0" * 16, 8), (7, fp["other words here now"], 7)}
    assert sh.near_duplicates(df).count() == 7
    assert sh.near_duplicates(df.limit(0)).count() == 0


def test_long_chain(spark):
    df = spark.createDataFrame([(i, i + 1) for i in range(80)], "a long, b long")
    label = sh.components(df).collect()
    assert len(label) == 81 and len({x.label for x in label}) == 1
