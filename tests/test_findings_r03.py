"""A test for each finding of the third review that led to a change."""

import datetime

import numpy as np
from framedelta import experiments
from framedelta.model import ReuseConfig
from framedelta.operators import encode, kernel, measures, store, tasks, training
from framedelta.plans.reference import epoch_plan
from framedelta.pretrained import modules
from framedelta.sources import frames as S
from pyspark.sql import functions as F


def test_every_scene_is_a_question_of_grounding(spark, small):
    """F5."""
    scenes = S.morph(spark, small).count() // 8
    assert scenes > 40 and {r.questions for r in experiments.grounding_tradeoff(spark, small).collect()} == {scenes}


def test_every_clip_is_a_query_of_retrieval(spark, small, monkeypatch):
    """F6."""
    asked = []
    recall = tasks.recall
    monkeypatch.setattr(tasks, "recall", lambda top, gold: (asked.append((gold.count(), top.select("query_id").distinct().count())), recall(top, gold))[1])
    assert experiments.retrieval_tradeoff(spark, small).count() == 5
    clips = S.morph(spark, small).count() // 8
    assert asked == [(clips, clips)] * 5


def test_no_frame_or_embedding_is_written_to_compare_ways(spark, small, monkeypatch):
    """rows are those of encoding each way on its own, and nothing but sums leaves the tasks."""
    monkeypatch.setattr(store, "written", None)
    ways = {"learned": [ReuseConfig(shift=1), "activity"], "budget": experiments.budget(2), "reset 8": experiments.mse(0.1, reset_every=8), "merge": (0, 1), "exact": None, "prune+merge": (1, 1)}
    f = S.activity(spark, small)
    got = {(r.method, r.fold): r for r in experiments.compared(f, experiments.TINY, ways).collect()}
    exact = encode.full_encode(f, experiments.TINY)
    fold = F.when(training.is_train(), "train").otherwise("held_out")
    for name, way in ways.items():
        z = experiments.encoded(f, experiments.TINY, *(way if isinstance(way, list) else (way,)))
        for want in measures.cosine_to_exact(z.withColumn("fold", fold), exact, ["fold"]).collect():
            one = got.pop((name, want.fold))
            for c in want.asDict():
                assert want[c] == one[c] or np.isclose(want[c], one[c], rtol=1e-9), (name, c)
    assert not got


def test_activity_frames_of_odd_events(spark, tmp_path):
    """unknown types and null values make no cell, but their users have frames; a cell is a tick's sum."""
    at = lambda hour: datetime.datetime(2024, 1, 1) + datetime.timedelta(hours=hour)
    rows = [(at(3), 7, "click", 5.0), (at(4), 7, "click", None), (at(5), 7, "click", 2.0), (at(200), 8, "odd", 2.0), (at(80), 9, None, 2.0), (at(90), 9, "view", None), (at(90), None, "view", 1.0), (None, 11, "view", 1.0)]
    spark.createDataFrame(rows, "ts timestamp_ntz, user_id long, event_type string, value double").write.parquet(f"{tmp_path}/events.parquet")
    f = S.activity(spark, str(tmp_path))
    assert "BroadcastNestedLoopJoin" in f._jdf.queryExecution().toString() and "SortMergeJoin" not in f._jdf.queryExecution().toString()
    got = {(r.video_id, r.frame_no): np.reshape(r.tokens, (6, 12)) for r in f.collect()}
    assert got.keys() == {(v, k) for v in (7, 8, 9) for k in range(1, 200 // 6 + 2)}
    for (v, k), x in got.items():
        want = np.zeros((6, 12))
        if v == 7 and k <= 12:
            want[1, 0], want[0, 0] = np.log1p(7.0), np.log1p(7.0) / 5
        assert np.allclose(x, want), (v, k)


def spied(monkeypatch) -> list:
    """The frames that the comparisons encode."""
    seen, real = [], encode.against_exact
    monkeypatch.setattr(encode, "against_exact", lambda frames, *more: (seen.append(frames), real(frames, *more))[1])
    return seen


def test_matrix_encodes_the_videos_that_it_shows(spark, small, monkeypatch):
    """F2."""
    seen = spied(monkeypatch)
    got = {r.kind: r.asDict() for r in experiments.method_matrix(spark, small).collect()}
    assert len(seen) == 2 and all(f.where(~training.is_train()).count() and not f.where(training.is_train()).count() for f in seen)
    for fixture, fn in (("activity", experiments.activity_tradeoff), ("shipping", experiments.shipping_tradeoff)):
        rows = [(r.method.split(" ")[0], r.cos_mean) for r in fn(spark, small).where("fold = 'held_out'").collect()]
        for kind, x in got.items():
            assert x[fixture] is None and not [c for k, c in rows if k == kind] or np.isclose(x[fixture], max(c for k, c in rows if k == kind))


def test_equal_accuracy_encodes_the_videos_that_it_asks_about(spark, small, monkeypatch):
    """F3."""
    seen = spied(monkeypatch)
    assert experiments.reuse_at_equal_accuracy(spark, small).count() > 0
    assert len(seen) == 1 and seen[0].where(~training.is_train()).count() and not seen[0].where(training.is_train()).count()


def test_frame_by_frame_costs_without_a_step_for_each_frame(monkeypatch):
    """each frame has its own multiplies, and what they cost is that of one epoch after the other."""
    raw = np.cumsum(np.random.default_rng(3).normal(size=(8 * 20, 6, 12)) * 0.05, 0)
    no, part = np.tile(np.arange(1, 21), 8), np.repeat(np.arange(8), 20)
    kind, wave, order, *refs = epoch_plan(no, np.full(160, 20))
    past, future = kernel.rows_of(no, part, *refs)
    calls, unit = [], kernel.unit
    monkeypatch.setattr(kernel, "unit", lambda *x: (calls.append(1), unit(*x))[1])
    for compaction in ("none", "frame"):
        for free in (False, True):
            cfg = ReuseConfig(schedule="frame", compaction=compaction, free_cache=free)
            calls.clear()
            all_ = kernel.gated(raw, past, future, kind, wave, experiments.TINY, cfg, modules("activity"), np.lexsort((order, part)))
            assert len(calls) < 160
            ones = [kernel.gated(raw[a : a + 20], np.where(past[a : a + 20] < 0, -1, past[a : a + 20] - a), np.where(future[a : a + 20] < 0, -1, future[a : a + 20] - a), kind[a : a + 20], wave[a : a + 20], experiments.TINY, cfg, modules("activity"), np.argsort(order[a : a + 20])) for a in range(0, 160, 20)]
            assert np.array_equal(all_.reuse, np.concatenate([x.reuse for x in ones])) and np.allclose(all_.emb, np.concatenate([x.emb for x in ones]))
            active = 6 - all_.reuse.sum(2) if compaction == "frame" else np.full((160, 2), 6)
            assert all_.count["multiplies"] == (active > 0).sum() and all_.count["rows"] == active.sum() and sorted(all_.rows) == sorted(active[active > 0])
            peaks = [x.count["peak"] for x in ones]
            assert all_.count["peak"] == (max(peaks) if free else sum(peaks)) and [x[1] for x in all_.trace[::3]][:1] == [0]


def test_schedules_move_the_tokens_once(spark, small):
    """F4."""
    x = experiments.schedule_costs(spark, small)
    assert x._jdf.queryExecution().optimizedPlan().toString().count("MapInArrow") == 2  # frames, and all schedules
    rows = {r.method: r for r in x.collect()}
    assert len(rows) == 7 and len({r.reuse_rate for r in rows.values()}) == 1
    assert rows["frame, none, kept"].multiplies > rows["layer, none, kept"].multiplies and rows["frame, frame, freed"].peak_bytes < rows["frame, frame, kept"].peak_bytes
