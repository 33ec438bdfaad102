import random

import corpus_pipeline as cp
from framedelta.llm import simhash as sh
from test_simhash import classes, slow_fingerprint


def test_one_of_each_by_fingerprint(spark):
    r = random.Random(9)
    base = [" ".join(f"w{r.randint(0, 10**6)}" for _ in range(400)) for _ in range(4)]
    rows = [(i, base[i % 3] + f" tail{i // 3}") for i in range(12)]
    rows += [(None, base[0]), (None, base[3]), (None, base[3] + " x"), (50, "alone here"), (50, "alone here"), (60, None), (61, ""), (70, "one text of seventy"), (70, "another text of seventy")]
    df = spark.createDataFrame([(*x, 7, "f") for x in rows], "doc_id long, text string, fp int, `class` string")
    got = sh.one_of_each(df).collect()
    codes = [slow_fingerprint(t) for _, t in rows]
    group = classes(codes, 3)
    want = {g: min((i for (i, _), h in zip(rows, group, strict=True) if h == g and i is not None), default=None) for g in set(group)}
    assert len(got) == len(want)
    of = dict(zip(codes, group, strict=True))
    assert {of[slow_fingerprint(x.text)]: x.doc_id for x in got} == want
    assert all(x.fp == 7 and x["class"] == "f" for x in got) and got[0].asDict().keys() == {"doc_id", "text", "fp", "class"}
    assert sh.one_of_each(df.limit(0)).count() == 0


def test_stages(spark, small, tmp_path):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    columns, before = docs.columns, docs.count()
    for name, stage in cp.STAGES[:-1]:
        stage(spark, docs, small).write.parquet(f"{tmp_path}/{name}")
        out = spark.read.parquet(f"{tmp_path}/{name}")
        assert out.columns == columns and out.dtypes == docs.dtypes
        assert 0.5 * before < out.count() <= docs.count(), name
        docs = out
    bench = [x.text for x in spark.read.parquet(f"{small}/benchmark.parquet").collect()]
    assert not any(" ".join(b.split()) in " ".join(x.text.split()) for x in docs.collect() for b in bench)
    packed = cp.STAGES[-1][1](spark, docs, small)
    assert packed.where("piece = 0").count() == docs.count()


def test_odd_rows_go_through(spark, tmp_path, small):
    import shutil

    rows = [(1, "the and of that " * 20, "en", None, 3, "x"), (None, "the and of this " * 20, None, "s", None, None), (3, None, "en", "s", 0, "y"), (4, "der die und das " * 30, "de", "s", 1, "z")]
    df = spark.createDataFrame(rows * 2, "doc_id long, text string, lang string, source string, n_chars long, score string")
    for part in (df, df.limit(0)):
        d = tmp_path / str(part.count())
        d.mkdir()
        part.write.parquet(f"{d}/documents.parquet")
        shutil.copy(f"{small}/benchmark.parquet", d)
        got = cp.run(spark, str(d)).collect()
        # the null text has no letters; of the repeated rows one stays
        assert sorted((x.doc_id is None, x.doc_id) for x in got) == ([(False, 1), (False, 4), (True, None)] if part is df else [])


def test_stages_against_plain_python(spark, tmp_path):
    """Each stage's decisions on a small table, worked out again without the operators."""
    import random

    from framedelta.llm.common import table

    r = random.Random(8)
    vocab = [f"{a}{b}" for a in ("the", "and", "ing", "tion", "er") for b in ("ly", "ed", "s", "ous", "al", "ic")]
    text = lambda n: " ".join(r.choice(vocab) + str(r.randint(0, 99)).translate(str.maketrans("0123456789", "abcdefghij")) for _ in range(n))
    base = [text(120) for _ in range(12)]
    near = [" ".join(w if i % 60 else "changed" for i, w in enumerate(b.split())) for b in base[:4]]
    bench = [text(30) for _ in range(3)]
    rows = [(i, t) for i, t in enumerate(base + near)] + [(50, text(40) + " " + bench[0] + " " + text(40)), (51, "1234 ... 99"), (52, base[5])]
    rows = [(i, t + "\nShared line of all") for i, t in rows]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(list(enumerate(bench)), "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    kept = cp.language(spark, docs, str(tmp_path))
    assert {x.doc_id for x in kept.collect()} == {i for i, t in rows if any(c.isalpha() for c in t)}
    out = cp.lines(spark, kept, str(tmp_path)).collect()
    assert all("Shared" not in x.text and x.n_chars == len(x.text) for x in out)
    left = cp.near_duplicates(spark, spark.createDataFrame(out, docs.schema), str(tmp_path)).collect()

    def shingles(t):
        w = t.lower().split()
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))}

    sets = {x.doc_id: shingles(x.text) for x in out}
    label = {i: i for i in sets}
    for a in sets:
        for b in sets:
            if a < b and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                old, new = max(label[a], label[b]), min(label[a], label[b])
                label = {k: new if v == old else v for k, v in label.items()}
    assert {x.doc_id for x in left} == set(label.values()) and len(set(label.values())) < len(label)
    clean = cp.decontaminated(spark, spark.createDataFrame(left, docs.schema), str(tmp_path)).collect()
    assert {x.doc_id for x in left} - {x.doc_id for x in clean} == {x.doc_id for x in left if any(b in x.text for b in bench)}
    assert table(spark, str(tmp_path), "benchmark").count() == 3


def test_tables_of_one_stage_do_not_stay_for_the_next(spark):
    """A worker that runs a second operator has dropped the first one's table."""
    from framedelta.llm import common

    df = spark.createDataFrame([(i, f"text {i}") for i in range(40)], "doc_id long, text string").repartition(2)

    def first(b):
        common.worker_state("first", lambda: bytearray(1 << 20))
        return b.select(["doc_id"])

    def second(b):
        import pyarrow as pa

        return pa.RecordBatch.from_arrays([pa.array([len(common._state)] * b.num_rows, pa.int32())], ["n"])

    for _ in range(2):
        assert common.map_text(df, first, "doc_id long").count() == 40
        assert {r.n for r in common.map_text(df, second, "n int").collect()} == {0}
