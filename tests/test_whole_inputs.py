"""Queries that must take their whole inputs."""

import hashlib

import numpy as np
from framedelta import experiments
from framedelta.operators import baselines, tasks
from framedelta.sources import frames as S
from pyspark.sql import functions as F


def test_talk_takes_whole_turns(spark, small, tmp_path):
    turns = [(7, 0, "a b c"), (7, 1, " ".join(f"w{i % 37}" for i in range(295))), (8, 5, " ".join(f"x{i}" for i in range(70))), (9, 0, "")]
    spark.createDataFrame(turns, "conv_id long, turn int, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    got = {(r.video_id, r.frame_no): np.array(r.tokens).reshape(9, 16) for r in S.talk(spark, str(tmp_path)).collect()}
    assert got.keys() == {(7, 1), (7, 2), (8, 1), (9, 1)}
    for key, (_, _, text) in zip([(7, 1), (7, 2), (8, 1), (9, 1)], turns, strict=True):
        w = text.split(" ")
        want = np.zeros((8, 16))
        for b in range(8):
            for x in w[len(w) * b // 8 : len(w) * (b + 1) // 8]:
                want[b, int(hashlib.md5(x.lower().encode()).hexdigest()[:6], 16) % 16] += 1
        assert np.allclose(got[key][1:], want) and np.allclose(got[key][0], want.mean(0))


def test_frame_search_takes_every_twentieth_frame(spark, small):
    got = experiments.frame_search(spark, small)
    frames = S.morph(spark, small)
    want = {r[0] for r in frames.where("frame_no % 20 = 0").select(F.col("video_id") * 1_000_000 + F.col("frame_no")).collect()}
    assert {r.query_id for r in got.collect()} == want and got.count() == 5 * len(want)


def test_frame_search_is_exact(spark):
    r = np.random.default_rng(3)
    x = r.normal(size=(900, 6)).round(1)
    x[100:400] = x[100]
    x[500] = 0
    z = spark.createDataFrame([(i % 7, i, v.tolist()) for i, v in enumerate(x)], "video_id long, frame_no int, emb array<double>")
    q = z.where("frame_no % 20 = 0").select(F.col("frame_no").cast("bigint").alias("query_id"), F.col("emb").alias("vec"))
    want = tasks.retrieve(q, z.select(F.struct("video_id", "frame_no").alias("clip_id"), "emb")).select("query_id", "clip_id.video_id", "clip_id.frame_no", F.round("score", 12), "rank")
    got = baselines.frame_search(q, z).withColumn("score", F.round("score", 12))
    assert got.dtypes[:3] == [("query_id", "bigint"), ("video_id", "bigint"), ("frame_no", "int")]
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
