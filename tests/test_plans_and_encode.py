import duckdb
import numpy as np
import pytest
from framedelta import experiments, workloads
from framedelta.functions import vector as V
from framedelta.model import EncoderSpec, ReuseConfig
from framedelta.operators import encode, kernel, measures, store, tasks
from framedelta.plans.reference import add_halo, plan_frames, training_groups
from framedelta.streaming.encoder import stream_encode
from pyspark.sql import functions as F

SPEC = EncoderSpec.preset("tiny")


@pytest.fixture(scope="module")
def frames(spark, tmp_path_factory):
    rows = []
    for v, n in ((1, 45), (2, 20), (3, 3), (4, 1), (5, 21)):
        x = np.cumsum(np.random.default_rng(v).normal(size=(n, 72)) * 0.2, 0)
        rows += [(v, i + 1, x[i].tolist()) for i in range(n)]
    path = str(tmp_path_factory.mktemp("f") / "frames")
    spark.createDataFrame(rows, "video_id long, frame_no int, tokens array<double>").write.parquet(path)
    return spark.read.parquet(path)


@pytest.mark.parametrize("scheme,tail", [("sequential", "chain"), ("reordered", "chain"), ("reordered", "short_anchor"), ("reordered", "recompute")])
def test_plan_invariants(frames, scheme, tail):
    plan = add_halo(plan_frames(frames, scheme, tail=tail)).collect()
    at = {(r.video_id, r.epoch_no, r.frame_no): r for r in plan}
    assert len(at) == len(plan) and sum(not r.is_halo for r in plan) == frames.count()
    for r in plan:
        for ref in (r.past_ref, r.future_ref):
            if ref is not None and not r.is_halo:
                o = at[r.video_id, r.epoch_no, ref]
                assert o.wavefront < r.wavefront and (o.is_halo or o.exec_order < r.exec_order)
    with pytest.raises(ValueError):
        plan_frames(frames, reset_every=10)


def test_training_groups(frames):
    g = training_groups(plan_frames(frames)).where("video_id = 1 and group_id = 1").orderBy("step").collect()
    assert [r.frame_no for r in g] == [1, 5, 9, 13, 11, 12]


def rows(df):
    return {(r.video_id, r.frame_no): (np.array(r.emb), r.reuse_rate) for r in df.collect()}


def test_encode_by_epochs_equals_the_kernel(frames):
    cfg = ReuseConfig(batch_epochs=1)
    one = rows(encode.gated_encode(frames, SPEC, cfg))
    many = rows(encode.gated_encode(frames.repartition(5), SPEC, ReuseConfig(batch_epochs=3), partitions=2))
    assert one.keys() == many.keys() and len(one) == 90
    assert all(np.allclose(one[k][0], many[k][0], atol=1e-9) and one[k][1] == many[k][1] for k in one)
    alone = rows(encode.gated_encode(frames.where("video_id = 5"), SPEC, cfg))
    assert all(np.allclose(one[k][0], v[0], atol=1e-9) for k, v in alone.items())
    exact = rows(encode.full_encode(frames, SPEC))
    assert np.allclose(one[1, 1][0], exact[1, 1][0]) and np.allclose(one[1, 21][0], exact[1, 21][0])


def test_no_reuse_is_not_shuffled(frames):
    plan = encode.gated_encode(frames, SPEC, ReuseConfig(gate="never"))._jdf.queryExecution().toString()
    assert "Exchange" not in plan
    assert encode.gated_encode(frames.limit(0), SPEC, ReuseConfig()).count() == 0


def test_ragged_frames_are_told(spark):
    bad = spark.createDataFrame([(1, 1, [0.0] * 71)], "video_id long, frame_no int, tokens array<double>")
    with pytest.raises(Exception, match="72 numbers"):
        encode.full_encode(bad, SPEC).collect()


@pytest.mark.parametrize("scheme", ["reordered", "sequential"])
def test_stream_equals_batch(spark, frames, tmp_path, scheme):
    cfg = ReuseConfig(scheme)
    parts = frames.orderBy("frame_no", "video_id").collect()
    src = tmp_path / "in"
    for i in range(0, len(parts), 30):
        spark.createDataFrame(parts[i : i + 30], frames.schema).coalesce(1).write.mode("append").parquet(str(src))
    stream = spark.readStream.schema(frames.schema).option("maxFilesPerTrigger", 1).parquet(str(src))
    q = stream_encode(stream, SPEC, cfg, kernel.new_modules(SPEC)).writeStream.format("memory").queryName(f"out_{scheme}").outputMode("append").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    got = rows(spark.table(f"out_{scheme}"))
    want = rows(encode.gated_encode(frames, SPEC, cfg, kernel.new_modules(SPEC)))
    assert spark.table(f"out_{scheme}").count() == len(got)
    assert len(got) >= (90 if scheme == "sequential" else 80)
    assert all(np.allclose(v[0], want[k][0], atol=1e-9) and np.isclose(v[1], want[k][1]) for k, v in got.items())


def test_requests_equal_rows_of_the_whole(frames):
    from framedelta.plans.rules import request

    cfg = ReuseConfig()
    whole = rows(encode.gated_encode(frames, SPEC, cfg))
    part = rows(request(frames, SPEC, cfg, videos=F.col("video_id").isin(1, 5), lo=18, hi=30))
    assert {k for k in whole if k[0] in (1, 5) and 18 <= k[1] <= 30} == part.keys()
    assert all(np.allclose(v[0], whole[k][0], atol=1e-9) for k, v in part.items())


def test_other_baselines(spark, frames):
    from framedelta.operators import baselines

    z = baselines.temporal_merge(frames, SPEC, 4)
    assert z.count() == 90 and z.agg(F.sum("flops")).first()[0] == pytest.approx(kernel.flops_exact(SPEC) * (12 + 5 + 1 + 1 + 6))
    v = spark.createDataFrame([(i, [1.0, 0.01 * i] if i % 2 else [0.01 * i, 1.0]) for i in range(20)], "id long, emb array<double>")
    c = {r.id: r.representative % 2 for r in baselines.cluster_index(v, k=2).collect()}
    assert len(c) == 20 and all(r == i % 2 for i, r in c.items())
    t = v.withColumns({"label": F.col("id") % 2, "is_train": F.col("id") < 12})
    a = baselines.proxy_cascade(t, v.select("id", (F.col("id") % 2).cast("int").alias("answer")))
    assert all(r.label == r.id % 2 for r in a.collect())


def test_store(spark, frames, tmp_path):
    s = store.EmbeddingStore(spark, f"file://{tmp_path}/s")
    some = frames.where("video_id <> 1 or frame_no <= 20")
    _, n = s.get_or_encode(some, "c", "m", SPEC, ReuseConfig())
    assert n == some.count()
    out, n = s.get_or_encode(frames, "c", "m", SPEC, ReuseConfig())
    assert n == 25 and out.count() == 90
    assert s.get_or_encode(frames, "c", "m", SPEC, ReuseConfig())[1] == 0
    v = spark.createDataFrame([([0.5, -1.25, 3.0],)], "v array<double>")
    assert v.select(store.decode_half(store.encode_half(F.col("v")))).first()[0] == [0.5, -1.25, 3.0]


def test_measures_and_tasks(spark):
    p = spark.createDataFrame([("a", "1", 0.9, 1.0, 0.1), ("a", "2", 0.8, 2.0, 0.5), ("b", "1", 0.8, 1.5, 0.3), ("b", "2", 0.95, 0.9, 0.0)], "method string, config string, accuracy double, flops_x double, reuse_rate double")
    assert {(r.method, r.config) for r in measures.pareto(p).collect()} == {("a", "1"), ("a", "2"), ("b", "2")}
    assert {r.method: r.flops_x for r in measures.best_within(p, 0.9).collect()} == {"a": 1.0, "b": 0.9}
    assert {r.method: round(r.reuse_rate, 3) for r in measures.reuse_at_accuracy(p, 0.85).collect()} == {"a": 0.3, "b": 0.2}
    spans = tasks.ground(spark.createDataFrame([(1, i, float(s)) for i, s in enumerate([0, 9, 9, 0, 8, 8, 8, 0])], "query_id int, frame_no int, score double"), 5)
    assert tuple(spans.first())[:3] == (1, 4, 6)
    iou = tasks.overlap(spans, spark.createDataFrame([(1, 5, 8), (2, 1, 2)], "query_id int, lo int, hi int"))
    assert {r.query_id: r.iou for r in iou.collect()} == {1: 2 / 5, 2: 0.0}
    clips = spark.createDataFrame([(i, [float(i == j) for j in range(3)]) for i in range(3)], "clip_id int, emb array<double>")
    top = tasks.retrieve(clips.select(F.col("clip_id").alias("query_id"), F.col("emb").alias("vec")), clips, 1)
    assert {(r.query_id, r.clip_id) for r in top.collect()} == {(0, 0), (1, 1), (2, 2)}
    a = tasks.answer(clips.select(F.col("clip_id").alias("query_id"), "emb"), clips.select(F.col("clip_id").alias("choice_no"), F.col("emb").alias("vec")))
    assert {(r.query_id, r.choice_no) for r in a.collect()} == {(0, 0), (1, 1), (2, 2)}


def test_sql_functions(spark):
    V.register(spark)
    assert spark.sql("select fd_cosine(array(1d, 0d), array(1d, 1d)) a, fd_cosine(array(0d), array(1d)) b, fd_mse(array(1d, 3d), array(0d, 0d)) c").first() == (1 / np.sqrt(2), 0.0, 5.0)


def plain(x):
    return round(x, 6) + 0.0 if isinstance(x, float) else x


@pytest.mark.parametrize("name", ["plan_reordered", "plan_tail_short_anchor", "training_groups_g3", "mse_gate_map", "budget_gate_map", "cache_trace", "retrieval_top5", "grounding_spans", "frames_morph", "frames_prose", "frames_pages", "frames_talk", "codec_hints", "ref_choice", "gate_mlp_literal", "compaction_positions", "cache_peak", "exact_embedding", "gated_embedding", "mse_gated_embedding", "budget_gated_embedding", "pruned_embedding", "temporal_merge_embedding", "cache_hits", "reuse_sites", "filtered_retrieval", "dedup_encode", "task_flops_share", "event_sessions", "event_frames_sliding", "event_props"])
def test_oracles(spark, small, name):
    con = duckdb.connect()
    for t in ("events", "documents", "labels", "embeddings", "lineitem", "pages", "conversations", "supplier", "nation", "region"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    df = workloads.QUERIES[name](spark, small)
    rel = con.sql(workloads.SQL[name])
    cols = sorted(df.columns)
    assert cols == sorted(rel.columns)
    want = con.sql(f"SELECT {', '.join(cols)} FROM ({workloads.SQL[name]})").fetchall()
    assert sorted(repr(tuple(map(plain, r))) for r in df.select(*cols).collect()) == sorted(repr(tuple(map(plain, r))) for r in want)


@pytest.mark.parametrize("scheme,tail", [("sequential", "chain"), ("reordered", "chain"), ("reordered", "short_anchor"), ("reordered", "recompute")])
def test_plan_in_the_task_equals_the_columns(frames, scheme, tail):
    from framedelta.model import TYPES
    from framedelta.plans.reference import epoch_plan

    plan = plan_frames(frames, scheme, tail=tail).collect()
    n = {}
    for r in plan:
        n[r.video_id] = max(n.get(r.video_id, 0), r.frame_no)
    f = np.array([r.frame_no for r in plan])
    last = np.array([min(n[r.video_id], (r.epoch_no + 1) * 20 + 1) for r in plan])
    kind, wave, order, past, future = epoch_plan(f, last, scheme, 20, tail)
    got = [(TYPES[k], int(w), int(o), int(p) or None, int(u) or None) for k, w, o, p, u in zip(kind, wave, order, past, future, strict=True)]
    assert got == [(r.ftype, r.wavefront, r.exec_order, r.past_ref, r.future_ref) for r in plan]


def test_more_than_one_task_encodes(spark, frames):
    z = encode.gated_encode(frames, SPEC, ReuseConfig()).withColumn("p", F.spark_partition_id())
    assert z.select("p").distinct().count() > 2
    plan = encode.gated_encode(frames, SPEC, ReuseConfig())._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1  # the tokens move once
    assert encode.partitions_for(frames, SPEC) == encode.encode_partitions(frames)


def test_lookback(frames):
    one, three = (rows(encode.gated_encode(frames, SPEC, ReuseConfig("sequential", lookback=k, gate="mse", theta=0.05, calibrator=False))) for k in (1, 3))
    assert one.keys() == three.keys() and any(one[k][1] != three[k][1] for k in one)
    assert all(np.allclose(one[k][0], three[k][0]) for k in ((1, 1), (1, 2), (2, 1)))


def test_reuse_can_be_set(frames):
    from framedelta.operators import training

    e = training.sample_epochs(frames, SPEC)
    m = kernel.new_modules(SPEC)
    cfg = training.at_reuse(e, SPEC, ReuseConfig(), m, 0.4)
    part, no, halo, raw = e
    kept = {int(p) for p in part}
    assert len(kept) == len({(int(p), int(n)) for p, n in zip(part[halo], no[halo], strict=True)}) or not halo.all()
    z = encode.gated_encode(frames.where(training.is_train()), SPEC, cfg, m).agg(F.avg("reuse_rate")).first()[0]
    assert abs(z - 0.4) < 0.1


def test_equal_exact_embeddings_are_made_once(spark, small):
    plan = experiments.compared(experiments.S.shipping(spark, small), experiments.SHIP, {"a": experiments.mse(0.1), "b": experiments.mse(0.5)})
    plan.collect()
    assert plan._jdf.queryExecution().executedPlan().toString().count("ReusedExchange") >= 1


def test_fitted_rates():
    from framedelta.operators import baselines

    x = np.cumsum(np.random.default_rng(5).normal(size=(60, 6, 12)), 0)
    prune, merge = baselines.fit_rates(x, SPEC, 1.5)
    z, flops = kernel.reduced(x, SPEC, prune, merge)
    assert flops * 1.5 <= kernel.flops_exact(SPEC)
    hand, cost = kernel.reduced(x, SPEC, 2, 0)
    assert kernel.cosine(z, kernel.exact(x, SPEC)).mean() > 0.5 and cost < kernel.flops_exact(SPEC)


def test_index_recall(spark, small):
    assert experiments.cluster_index_recall(spark, small).first().recall >= 0.9


def test_prepared_modules_come_back(spark, frames, tmp_path):
    path = f"file://{tmp_path}/w"
    many = frames.unionByName(frames.where("video_id = 1").withColumn("video_id", F.lit(6).cast("bigint"))).unionByName(frames.where("video_id = 1").withColumn("video_id", F.lit(7).cast("bigint")))
    i = store.prepare(many, SPEC, 0.5, path, steps=2)
    m = store.saved_modules(spark, path, i)
    assert [sorted(x) for x in m] == [sorted(x) for x in kernel.new_modules(SPEC)]
    assert all(a[k].shape == b[k].shape for a, b in zip(m, kernel.new_modules(SPEC), strict=True) for k in b)
    assert encode.gated_encode(frames, SPEC, ReuseConfig(), m).count() == 90


def test_replayed_batches_are_stored_once(spark, frames, tmp_path):
    s = store.EmbeddingStore(spark, f"file://{tmp_path}/s")
    z = encode.full_encode(frames, SPEC)
    for _ in range(2):
        s.append(z, "c", "m", batch="one")
    assert spark.read.parquet(s.path).count() == 90
    s.append(z, "c", "m", batch="two")
    assert s.read("c", "m").count() == 90
    src = str(tmp_path / "in")
    z.coalesce(1).write.parquet(src)
    q = s.sink(spark.readStream.schema(z.schema).parquet(src), "stream", "m", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert s.read("stream", "m").count() == 90


def test_a_gap_is_closed(spark, frames, tmp_path):
    src = str(tmp_path / "in")
    f = frames.where("video_id = 1 and frame_no <> 7")
    f.coalesce(1).write.parquet(src)
    stream = spark.readStream.schema(frames.schema).parquet(src)
    q = stream_encode(stream, SPEC, ReuseConfig("sequential"), kernel.new_modules(SPEC), max_ahead=10).writeStream.format("memory").queryName("gap").outputMode("append").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    got = sorted(r.frame_no for r in spark.table("gap").collect())
    assert got == [i for i in range(1, 46) if i != 7]


def test_streams_are_joined(spark, tmp_path, small):
    from framedelta.streaming import encoder as E

    e = spark.createDataFrame([(1, "2024-01-01 00:00:00", 1.0), (1, "2024-01-02 00:00:00", 2.0), (2, "2024-01-01 00:00:00", 3.0)], "user_id long, ts string, value double").withColumn("ts", F.col("ts").cast("timestamp"))
    n = spark.createDataFrame([(1, "2024-01-01 03:00:00", "x"), (1, "2024-01-01 09:00:00", "y"), (2, "2024-01-01 00:00:00", "z")], "user_id long, note_ts string, note string").withColumn("note_ts", F.col("note_ts").cast("timestamp"))
    for k, df in (("e", e), ("n", n)):
        df.coalesce(1).write.parquet(str(tmp_path / k))
    read = lambda k, df: spark.readStream.schema(df.schema).parquet(str(tmp_path / k))
    q = E.annotated(read("e", e), read("n", n)).writeStream.format("memory").queryName("notes").outputMode("append").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert sorted((r.user_id, r.note) for r in spark.table("notes").collect()) == [(1, "x"), (2, "z")]
    z = spark.createDataFrame([(1, 1, [1.0, 0.0]), (1, 2, [0.0, 1.0])], "video_id long, frame_no int, emb array<double>")
    z.coalesce(1).write.parquet(str(tmp_path / "z"))
    asked = spark.createDataFrame([(9, [1.0, 0.1])], "query_id long, vec array<double>")
    q = E.scored(spark.readStream.schema(z.schema).parquet(str(tmp_path / "z")), asked, 0.5).writeStream.format("memory").queryName("hits").outputMode("append").option("checkpointLocation", str(tmp_path / "c2")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert [(r.query_id, r.frame_no) for r in spark.table("hits").collect()] == [(9, 1)]
    assert E.queue_latency() == 2.0


def test_table_functions(spark, frames):
    from framedelta.functions import tables

    tables.register(spark)
    got = spark.sql("SELECT * FROM fd_plan(45, 'reordered', 20)").collect()
    want = {r.frame_no: (r.ftype, r.past_ref, r.future_ref, r.wavefront) for r in plan_frames(frames.where("video_id = 1")).collect()}
    assert {r.frame_no: (r.ftype, r.past_ref, r.future_ref, r.wavefront) for r in got} == want
    assert [r.frame_no for r in spark.sql("SELECT * FROM fd_group(1, 3, 'reordered')").collect()] == [1, 5, 9, 13, 11, 12]
    assert [r.live for r in spark.sql("SELECT * FROM fd_cache_steps(24, 3) ORDER BY step").collect()] == [r.live_units for r in measures.cache_trace(spark, EncoderSpec.preset("large")).orderBy("step").collect()]
    assert spark.sql("SELECT fd_vector_mean(v) m FROM VALUES (array(1d, 2d)), (array(3d, 6d)) t(v)").first().m == [2.0, 4.0]
    c = tasks.clips(frames.where("video_id = 2"), 8).select("clip_id.clip").distinct().count()
    assert c == 3
    n = spark.createDataFrame([(1, 3.4), (2, 9.0)], "query_id int, estimate double")
    assert {r.query_id: r.choice_no for r in tasks.count_answer(n, [1, 3, 5]).collect()} == {1: 3, 2: 5}
