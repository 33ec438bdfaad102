"""A test for each finding of the second review that led to a change."""

import datetime

import numpy as np
from framedelta import workloads
from framedelta.functions import vector as V
from framedelta.operators import search
from pyspark.sql import Window
from pyspark.sql import functions as F


def plan(df) -> str:
    return df._jdf.queryExecution().toString()


def no_pairs(df) -> bool:
    """Whether no pair of a query and another row becomes a row."""
    return not any(x in plan(df) for x in ("NestedLoopJoin", "CartesianProduct"))


def test_equal_totals_are_equal_in_any_order_of_addition(spark, tmp_path):
    """a run of 100.3 and a later one of 50.1 and 50.2, whose sum as doubles is a little more."""
    at = lambda tick: datetime.datetime(2024, 1, 1, 1) + datetime.timedelta(hours=6 * tick)
    rows = [(0, at(0), 7, "purchase", 100.3, "{}"), (1, at(2), 7, "purchase", 50.1, "{}"), (2, at(3), 7, "purchase", 50.2, "{}")]
    spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string").write.parquet(f"{tmp_path}/events.parquet")
    assert 50.1 + 50.2 > 100.3
    assert [tuple(r) for r in workloads.grounding_spans(spark, str(tmp_path)).collect()] == [(7, 1, 1)]


def test_retrieval_makes_no_row_of_a_pair(spark, small):
    """F8."""
    assert no_pairs(workloads.retrieval_top5(spark, small))


def test_search_equals_brute_force(spark):
    """F8: equal vectors, zero and null ones, clips of several rows, and parts."""
    r = np.random.default_rng(5)
    x = r.normal(size=(700, 6)).round(1)
    x[100:400] = x[100]
    x[500] = 0
    rows = [(i * 37 % 701, i // 3, None if i == 600 else v.tolist(), i % 4) for i, v in enumerate(x)]
    e = spark.createDataFrame(rows, "id long, doc long, emb array<double>, part int").repartition(5)
    q = e.where("id % 20 = 0").select(F.col("id").alias("query_id"), F.col("emb").alias("vec"), F.array(F.lit(0), (F.col("part") % 3 + 1).cast("int")).alias("parts"))
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "clip_id")
    score = V.cosine(F.col("vec"), F.col("emb"))
    for clip, digits, parts in (("id", None, False), ("id", 2, False), ("doc", None, False), ("id", None, True)):
        got = search.nearest(q if parts else q.drop("parts"), e.select(F.col(clip).alias("clip_id"), "emb", *(["part"] if parts else [])), 5, digits, clip == "doc")
        y = e.crossJoin(q.select("query_id", "vec", "parts")).where(F.array_contains("parts", F.col("part")) if parts else F.lit(True))
        y = y.groupBy("query_id", F.col(clip).alias("clip_id")).agg(F.max(score if digits is None else F.round(score, digits)).alias("score"))
        want = y.withColumn("rank", F.row_number().over(w)).where("rank <= 5")
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect())), (clip, digits, parts)


def test_index_makes_no_row_of_a_pair(spark, small):
    """F4, F5."""
    from framedelta import experiments

    assert no_pairs(experiments.cluster_index(spark, small))


def test_runs_by_peak_equal_all_scores(spark):
    """scenes are found as by a row for each question and frame, across stretches and gaps, and no such row is made."""
    from framedelta.operators import tasks

    r = np.random.default_rng(2)
    x = np.repeat(r.normal(size=(300, 3)).round(1), 12, axis=0)
    x[2100:2500] = x[2100]
    z = spark.createDataFrame([(i % 2, i // 2 + (i > 3000), v.tolist()) for i, v in enumerate(x)], "video_id long, frame_no int, emb array<double>").repartition(3)
    q = z.where("frame_no % 150 = 7").select(F.struct("video_id", "frame_no").alias("query_id"), F.col("emb").alias("vec"))
    one = search.runs_by_peak(q, z, 0.75)
    assert no_pairs(one)
    y = z.crossJoin(q).select(F.struct("query_id", "video_id").alias("query_id"), "frame_no", V.cosine(F.col("vec"), F.col("emb")).alias("score"))
    y = tasks.ground(y, 0.75, by="peak").select("query_id.*", "lo", "hi", "total")
    want = y.groupBy("query_id").agg(F.max(F.struct("total", (-F.col("video_id")).alias("v"), (-F.col("lo")).alias("l"), "hi")).alias("m")).select("query_id", -F.col("m.v"), -F.col("m.l"), "m.hi", "m.total")
    assert sorted(map(tuple, one.collect())) == sorted(map(tuple, want.collect()))


def test_costs_are_those_of_the_conversations(spark, tmp_path):
    """F15 to F22: closed forms over a given table, so another table gives other results."""
    import duckdb

    got = {}
    for name, videos in (("a", {1: 9, 2: 3}), ("b", {5: 21, 6: 1, 7: 30} | {i: 2 for i in range(100, 600)})):
        rows = [(v, t, f"turn {t} of {v}" if t != 1 else "a") for v, n in videos.items() for t in range(n)] + [(None, 0, "x"), (9, 0, None)]
        spark.createDataFrame(rows, "conv_id long, turn int, text string").write.parquet(f"{tmp_path}/{name}/conversations.parquet")
        con = duckdb.connect()
        con.sql(f"CREATE VIEW conversations AS SELECT * FROM '{tmp_path}/{name}/conversations.parquet/*.parquet'")
        for q in ("cache_peak", "cache_trace", "flops_breakdown", "layer_flops", "max_batch", "reset_overhead", "reuse_sites", "storage_overhead"):
            df = workloads.QUERIES[q](spark, f"{tmp_path}/{name}")
            got[name, q] = sorted(map(tuple, df.collect()))
            assert got[name, q] == sorted(con.sql(f"SELECT {', '.join(df.columns)} FROM ({workloads.SQL[q]})").fetchall()), q
            assert name == "a" or got["a", q] != got["b", q], q


def test_passages_are_found_as_by_contains(spark):
    """words in part, spaces in a row, empty and short passages, repeated rows; no row of a passage and a text."""
    texts = ["", "a b", "xa bc dy", "a b  c d", "a b c d", "the end of it", None, "Ü ä b  c", "a b c d"]
    passages = ["a b c", "b  c", "", "a bc d", "d", "nd of i", " b c ", "ä b  c", None, "a b c"]
    d = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "clip_id long, text string")
    b = spark.createDataFrame([(i // 2, p) for i, p in enumerate(passages)], "query_id long, passage string")
    got = search.holding(b, d)
    assert no_pairs(got)
    want = d.join(b, F.col("text").contains(F.col("passage"))).select("query_id", "clip_id")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_scrolled_frames_count_a_block_once(spark):
    """frames as counted window by window, of texts that end anywhere, across the bounds of arrays; made without lambda functions of rows."""
    from framedelta.sources import frames as S

    r = np.random.default_rng(1)
    rows = {i: r.integers(0, 16, n).tolist() for i, n in enumerate([0, 1, 63, 64, 65, 80, 81, 700, 3, 129])}
    units, frames = S.SCROLL_UNITS, S.SCROLL_FRAMES
    S.SCROLL_UNITS, S.SCROLL_FRAMES = 100, 7
    try:
        df = spark.createDataFrame(list(rows.items()), "video_id long, h array<int>").coalesce(1)
        out = S.scrolled(df, F.col("h"))
        assert "lambdafunction" not in plan(out)
        got = {(x.video_id, x.frame_no): x.tokens for x in out.collect()}
    finally:
        S.SCROLL_UNITS, S.SCROLL_FRAMES = units, frames
    want = {}
    for v, h in rows.items():
        for f in range(max(1, -(-(len(h) - 64) // 16) + 1)):
            part = [np.bincount(h[(2 * f + k) * 8 : (2 * f + k + 1) * 8], minlength=16) for k in range(8)]
            ring = np.array([part[(s - 2 * f) % 8] for s in range(8)], float)
            want[v, f + 1] = [*(ring.sum(0) / 8), *ring.ravel()]
    assert got == want


def test_directions_come_from_all_documents(spark, monkeypatch):
    """every document is a row of the matrix, however many there are; together they weigh as much as was asked for."""
    from framedelta.llm import decontam_lsa as dl

    seen = []
    made = dl.singular_vectors
    monkeypatch.setattr(dl, "singular_vectors", lambda p, *a, **k: (seen.append((p.count(), p.agg(F.sum(F.col("weight") ** 2)).first()[0] if "weight" in p.columns else None)), made(p, *a, **k))[1])
    docs = spark.createDataFrame([(i, f"word{i % 7} word{i % 11} some text of document {i}") for i in range(300)] + [(300, None)], "doc_id long, text string")
    bench = spark.createDataFrame([(1, "word1 word2 some text of document"), (2, "word5 word5 some text of document")], "item_id long, text string")
    found = dl.leaks(docs, bench, background_passages=20)
    assert [n for n, _ in seen] == [303] and abs(seen[0][1] - 22) < 1e-6
    assert {x.item_id for x in found.collect()} <= {1, 2}


def test_frames_between_key_frames_are_made_outside_the_label_s_task(spark, tmp_path):
    """mixes in the order of SQL's sums; the frames are made after a shuffle that follows the window, and not by lambda functions of rows."""
    from framedelta.sources import frames as S

    r = np.random.default_rng(4)
    x = r.normal(size=(9, 64)).astype(np.float32)
    rows = [(i * 3, v.tolist(), i % 2) for i, v in enumerate(x)] + [(100, None, 0), (101, x[0].tolist(), None)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    out = S.morph(spark, str(tmp_path))
    assert "lambdafunction" not in plan(out)
    want = {}
    for label in (0, 1):
        keys = x[label::2].astype(float)
        for n, (a, b) in enumerate(zip(keys, keys[1:])):
            for j in range(8):
                p = (a * (8 - j) / 8 + b * j / 8).reshape(8, 8)
                want[label, n * 8 + j + 1] = [*(sum(p, np.zeros(8)) / 8), *p.ravel()]
    assert {(f.video_id, f.frame_no): f.tokens for f in out.collect()} == want


def test_no_stage_of_the_pipeline_holds_two_python_maps(spark, tmp_path, monkeypatch):
    """pipeline: Spark keeps a Python process for each map of a stage's tasks, so two of them in a stage double what an executor's Python takes."""
    import corpus_pipeline as cp

    seen = []
    frame = type(spark.range(0))
    made = frame.mapInArrow

    def same_stage(p) -> list[str]:
        if "Exchange" in p.nodeName():
            return []
        below = p.executedPlan() if p.nodeName() == "AdaptiveSparkPlan" else None
        kids = [below] if below is not None else [p.children().apply(i) for i in range(p.children().size())]
        return [p.nodeName(), *(x for k in kids for x in same_stage(k))]

    def mapped(self, fn, *a, **k):
        seen.append((fn.__qualname__, same_stage(self._jdf.queryExecution().executedPlan())))
        return made(self, fn, *a, **k)

    monkeypatch.setattr(frame, "mapInArrow", mapped)
    bench = " ".join(f"quiz{i} item{i}" for i in range(15))
    text = lambda i: " ".join(f"w{(i // 2) * 97 + k}" for k in range(120))
    rows = [(i, text(i) + (" tail" if i % 2 else "") + (f" {bench}" if i in (4, 9) else "") + f"\nline {i % 2} of all", "en" if i % 3 else "de", "s", 1) for i in range(40)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, bench)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    cp.run(spark, str(tmp_path)).collect()
    assert len(seen) > 10
    assert [(who, x) for who, names in seen for x in names if x == "MapInArrow" or "ExistingRDD" in x] == []
