"""The embedding store: Parquet by corpus and model, hits by an anti join, misses encoded in whole epochs."""

from __future__ import annotations

import tempfile
import uuid

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import EncoderSpec, ReuseConfig
from . import encode


def new_path(spark: SparkSession, name: str) -> str:
    """A new path in the folder that all executors share, spark.checkpoint.dir. Only a local master may do without one: it has no other machine."""
    known = spark.conf.get("spark.checkpoint.dir", None)
    if not known:
        master = spark.sparkContext.master
        if not (master == "local" or master.startswith("local[")):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        known = "file://" + tempfile.mkdtemp(prefix="framedelta-shared-")
    return f"{known.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def written(df: DataFrame, name: str) -> DataFrame:
    """df written once and read from there: later uses do not make it again, and a lost executor does not either."""
    path = new_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


class EmbeddingStore:
    """path may be in any file system that Spark writes. A model_id names encoder, options and weights: another gate is another embedding.

    A write has a batch name and replaces what an earlier try of that batch left, so retried and replayed writes store nothing twice. Frames that
    two concurrent requests stored are read once.
    """

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")
        self.schema = "video_id bigint, frame_no int, emb array<double>, reuse_rate double, flops double, corpus string, model_id string, batch string"

    def read(self, corpus: str, model_id: str) -> DataFrame:
        try:
            df = self.spark.read.schema(self.schema).parquet(self.path)
        except Exception as e:  # nothing stored yet
            if "PATH_NOT_FOUND" not in str(e):
                raise
            df = self.spark.createDataFrame([], self.schema)
        df = df.where((F.col("corpus") == corpus) & (F.col("model_id") == model_id))
        one = df.groupBy("video_id", "frame_no").agg(F.min_by(F.struct("emb", "reuse_rate", "flops"), "batch").alias("x"))
        return one.select("video_id", "frame_no", "x.*")

    def append(self, df: DataFrame, corpus: str, model_id: str, batch: str | None = None, codec: str = "zstd") -> None:
        """Store df. With a batch name, what that batch wrote before is replaced. codec compresses the files."""
        df = df.select("video_id", "frame_no", "emb", "reuse_rate", "flops").withColumns({"corpus": F.lit(corpus), "model_id": F.lit(model_id), "batch": F.lit(batch or uuid.uuid4().hex)})
        w = df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").option("compression", codec)
        # doubles of neighbouring frames share their high bytes: kept byte by byte they compress
        w.option("parquet.enable.dictionary", "false").option("parquet.enable.bytestreamsplit", "true").partitionBy("corpus", "model_id", "batch").parquet(self.path)

    def get_or_encode(self, frames: DataFrame, corpus: str, model_id: str, spec: EncoderSpec, cfg: ReuseConfig, modules=None) -> tuple[DataFrame, int]:
        """(EMBEDDINGS of all frames, how many had to be encoded). A missing frame brings its whole epoch, or its value would differ."""
        have = self.read(corpus, model_id).select("video_id", "frame_no")
        epoch = F.floor((F.col("frame_no") - 1) / cfg.reset_every)
        missing = frames.select("video_id", "frame_no").join(have, ["video_id", "frame_no"], "left_anti")
        n = missing.count()
        if n:
            missing = written(missing, "missing")
            videos = missing.select("video_id", epoch.alias("_e")).distinct()
            # the closing anchor of an epoch is the next one's first frame
            near = videos.select("video_id", F.explode(F.array(F.col("_e"), F.col("_e") + 1)).alias("_e")).distinct()
            todo = frames.withColumn("_e", epoch).join(near, ["video_id", "_e"], "left_semi").drop("_e")
            self.append(encode.gated_encode(todo, spec, cfg, modules).join(missing, ["video_id", "frame_no"], "left_semi"), corpus, model_id)
        return self.read(corpus, model_id).join(frames.select("video_id", "frame_no"), ["video_id", "frame_no"], "left_semi"), n

    def sink(self, stream: DataFrame, corpus: str, model_id: str, checkpoint: str):
        """A streaming query that stores a stream of embeddings; a replayed micro-batch replaces itself."""

        def put(part: DataFrame, number: int) -> None:
            if "flops" not in part.columns:
                part = part.withColumn("flops", F.lit(None).cast("double"))
            self.append(part, corpus, model_id, batch=f"stream-{number}")

        return stream.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint)

    def stats(self) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(self.path).groupBy("corpus", "model_id").agg(F.count(F.lit(1)).alias("frames"), F.sum(F.size("emb")).alias("numbers"))


def prepare(frames: DataFrame, spec: EncoderSpec, r_target: float, path: str, segments: int = 3, groups: int = 600, **options) -> str:
    """Offline preparation of a corpus: fit gates and calibrators to a bounded sample of its training videos and write them under path; the model_id.

    Rows of the written table are (model_id, layer, part, i, j, w).
    """
    import hashlib

    from . import training

    g = training.sample_groups(frames, spec, segments, groups)
    if not len(g):
        raise ValueError("no whole group of frames to learn from")
    modules, _ = training.fit_reuse(g, spec, r_target=r_target, segments=segments, **options)
    model_id = hashlib.sha256(repr((spec, r_target, segments, sorted(options.items()), [m["g1"].tolist() for m in modules])).encode()).hexdigest()[:16]
    rows = [(model_id, layer, part, int(i), int(j), float(np.atleast_2d(w)[i, j])) for layer, m in enumerate(modules) for part, w in m.items() for i, j in np.ndindex(np.atleast_2d(w).shape)]
    frames.sparkSession.createDataFrame(rows, "model_id string, layer int, part string, i int, j int, w double").coalesce(1).write.mode("append").partitionBy("model_id").parquet(path)
    return model_id


def saved_modules(spark: SparkSession, path: str, model_id: str) -> list[dict]:
    """The modules that prepare() wrote."""
    rows = spark.read.parquet(path).where(F.col("model_id") == model_id).collect()
    out: list[dict] = [{} for _ in range(1 + max(r["layer"] for r in rows))]
    for layer, part in {(r["layer"], r["part"]) for r in rows}:
        cells = [r for r in rows if (r["layer"], r["part"]) == (layer, part)]
        m = np.zeros((1 + max(r["i"] for r in cells), 1 + max(r["j"] for r in cells)))
        for r in cells:
            m[r["i"], r["j"]] = r["w"]
        out[layer][part] = m if part in ("g1", "g2", "c1", "c2") else m[0]
    return out


def encode_half(vec):
    """An array of numbers as little-endian half-precision bytes."""
    @F.pandas_udf("binary")
    def half(s: pd.Series) -> pd.Series:
        known = s.notna().to_numpy()
        size = np.fromiter((len(v) for v in s[known]), np.int64, known.sum())
        flat = (np.concatenate(s[known].to_list()) if known.any() else np.empty(0)).astype("<f2").tobytes()
        ends = 2 * np.cumsum(size)
        out = np.full(len(s), None, object)
        out[known] = [flat[e - 2 * n : e] for e, n in zip(ends.tolist(), size.tolist(), strict=True)]
        return pd.Series(out)

    return half(vec)


def decode_half(data):
    @F.pandas_udf("array<double>")
    def whole(s: pd.Series) -> pd.Series:
        return s.map(lambda v: None if v is None else np.frombuffer(v, "<f2").astype(float))

    return whole(data)
