"""Costs and accuracies: FLOPs, cache traces, storage, trade-off points."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import vector as V
from ..model import EncoderSpec


def layer_flops(spark: SparkSession, specs: dict[str, EncoderSpec]) -> DataFrame:
    """name, part, flops, share: of one layer and frame."""
    rows = []
    for name, s in specs.items():
        n, d = s.n_tokens, s.dim
        rows += [(name, "qkv", 6 * n * d * d), (name, "attention", 4 * n * n * d), (name, "projection", 2 * n * d * d), (name, "ffn", 4 * s.ffn_mult * n * d * d)]
    df = spark.createDataFrame(rows, "name string, part string, flops bigint")
    return df.withColumn("share", F.col("flops") / F.sum("flops").over(Window.partitionBy("name")))


def flops_breakdown(spark: SparkSession, spec: EncoderSpec, rates: list[float]) -> DataFrame:
    """reuse_rate, part, flops and share of the exact encoder's, of one layer with the calibrator's QKV output."""
    n, d = spec.n_tokens, spec.dim
    r = F.col("reuse_rate") * n
    parts = {"qkv": 6 * d * d * (n - r), "ffn": 4 * spec.ffn_mult * d * d * (n - r), "attention": F.lit(4.0 * n * n * d + 2.0 * n * d * d), "calibrator": r * 2 * spec.hidden * 4 * d, "gate": F.lit(float((n - 1) * (2 * 8 * 16 + 2 * 16 + 12 * d)))}
    df = spark.createDataFrame([(float(x),) for x in rates], "reuse_rate double")
    x = df.select("reuse_rate", F.inline(F.array(*[F.struct(F.lit(k).alias("part"), v.cast("double").alias("flops")) for k, v in parts.items()])))
    return x.withColumn("share", F.col("flops") / float((8 + 4 * spec.ffn_mult) * n * d * d + 4 * n * n * d))


def reset_overhead(spark: SparkSession, periods: list[int], rho: float, share: float) -> DataFrame:
    """What a fully computed frame every `reset_every` frames adds, as a part of the exact cost."""
    return spark.createDataFrame([(k,) for k in periods], "reset_every int").withColumn("overhead", F.lit(rho * share) / F.col("reset_every"))


def storage_overhead(spark: SparkSession, fps: float = 2.0, dim: int = 1024, bytes_per: int = 2, video_rate: float = 625_000.0) -> DataFrame:
    return spark.createDataFrame([(fps * dim * bytes_per, fps * dim * bytes_per / video_rate)], "bytes_per_second double, share double")


def cache_trace(spark: SparkSession, spec: EncoderSpec, frames: int = 5, segments: int = 3, schedule: str = "layer", free_cache: bool = True) -> DataFrame:
    """step, layer, segment, live_units: cached frames x layers after each layer (of each frame, where frames go one by one) of some segments.

    Layer by layer with freeing, the four frames of a segment live for one layer, and the closing anchor's caches of all layers stay.
    """
    n, layers = frames - 1, spec.layers
    if schedule == "frame":
        x = spark.range(segments * n * layers).select(F.col("id").cast("int").alias("step"))
        x = x.select("step", F.pmod("step", F.lit(layers)).alias("layer"), F.floor(F.col("step") / (n * layers)).cast("int").alias("segment"))
        alloc, free = F.lit(1), F.lit(0)
        if free_cache:
            free = F.when((F.pmod("step", F.lit(n * layers)) == n * layers - 1), n * layers - layers + F.when(F.col("segment") > 0, layers).otherwise(0)).otherwise(0)
    else:
        x = spark.range(segments * layers).select(F.col("id").cast("int").alias("step"))
        x = x.select("step", F.pmod("step", F.lit(layers)).alias("layer"), F.floor(F.col("step") / layers).cast("int").alias("segment"))
        alloc = F.lit(n)
        # after a layer all but the new anchor go, and with them the layer's old anchor
        free = (F.lit(n - 1) + F.when(F.col("segment") > 0, 1).otherwise(0)) if free_cache else F.lit(0)
    live = F.sum("alloc").over(Window.orderBy("step")) - F.coalesce(F.sum("free").over(Window.orderBy("step").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return x.withColumns({"alloc": alloc.cast("bigint"), "free": free.cast("bigint")}).withColumn("live_units", live)


def reuse_sites(spark: SparkSession, spec: EncoderSpec) -> DataFrame:
    """layer, part, reusable, flops of a token: which parts of each layer may be reused. Parts that mix tokens are computed, and so is the first QKV, which no class attention precedes."""
    n, d = spec.n_tokens, spec.dim
    parts = {"qkv": 6 * d * d, "attention": 4 * n * d, "projection": 2 * d * d, "ffn": 4 * spec.ffn_mult * d * d}
    rows = [(layer, part, part == "ffn" or (part == "qkv" and layer > 0), flops) for layer in range(spec.layers) for part, flops in parts.items()]
    return spark.createDataFrame(rows, "layer int, part string, reusable boolean, flops bigint")


def max_batch(spark: SparkSession, cap_bytes: int, spec: EncoderSpec, fixed_bytes: int = 0, bytes_per: int = 2) -> DataFrame:
    """Videos that fit at once under a memory cap, with and without freed caches: peaks of 5 L and L + 4 units."""
    unit = spec.n_tokens * 4 * spec.dim * bytes_per
    rows = [("none", 5 * spec.layers * unit), ("freed", (spec.layers + 4) * unit)]
    return spark.createDataFrame(rows, "caches string, peak_bytes bigint").withColumn("max_batch", F.floor((F.lit(cap_bytes) - fixed_bytes) / F.col("peak_bytes")).cast("bigint"))


def cosine_to_exact(approx: DataFrame, exact: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Mean, least and 5th-percentile cosine, mean reuse, and exact over approximate FLOPs."""
    b = exact.select("video_id", "frame_no", F.col("emb").alias("_z"), F.col("flops").alias("_full"))
    x = approx.join(b, ["video_id", "frame_no"]).withColumn("_c", V.cosine(F.col("emb"), F.col("_z")))
    return fidelity(x, by or [], "_c", "_full")


def fidelity(x: DataFrame, by: list[str], cosine: str = "cosine", full: str = "full") -> DataFrame:
    """cosine_to_exact of frames that have their cosine and the exact encoder's FLOPs."""
    c = F.col(cosine)
    return x.groupBy(*by).agg(F.avg(c).alias("cos_mean"), F.min(c).alias("cos_min"), F.percentile_approx(c, 0.05).alias("cos_p05"), F.avg("reuse_rate").alias("reuse_rate"), (F.sum(full) / F.sum("flops")).alias("flops_x"), F.count(F.lit(1)).alias("frames"))


def pareto(points: DataFrame, x: str = "accuracy", y: str = "flops_x") -> DataFrame:
    """Points that no other is at least as good as in both and better in one."""
    b = F.broadcast(points.select(F.col(x).alias("_x"), F.col(y).alias("_y")))
    better = (F.col("_x") >= F.col(x)) & (F.col("_y") >= F.col(y)) & ((F.col("_x") > F.col(x)) | (F.col("_y") > F.col(y)))
    return points.join(b, better, "left_anti")


def best_within(points: DataFrame, exact_accuracy: Column | float, bound: float = 0.02, relative: bool = True, speed: str = "flops_x") -> DataFrame:
    """For each method, the greatest speed whose accuracy is within the bound of the exact encoder's."""
    base = exact_accuracy if isinstance(exact_accuracy, Column) else F.lit(exact_accuracy)
    least = base * (1 - bound) if relative else base - bound
    return points.where(F.col("accuracy") >= least).groupBy("method").agg(F.max(speed).alias(speed), F.max_by("config", F.col(speed)).alias("config"))


def reuse_at_accuracy(points: DataFrame, accuracy: float) -> DataFrame:
    """For each method, the reuse rate at an accuracy by linear interpolation between neighbouring points; none outside of them."""
    w = Window.partitionBy("method").orderBy("accuracy")
    a0, r0 = F.lag("accuracy").over(w), F.lag("reuse_rate").over(w)
    x = points.select("method", "accuracy", "reuse_rate", a0.alias("a0"), r0.alias("r0")).where((F.col("a0") <= accuracy) & (F.col("accuracy") >= accuracy) & (F.col("accuracy") > F.col("a0")))
    at = F.col("r0") + (F.col("reuse_rate") - F.col("r0")) * (F.lit(accuracy) - F.col("a0")) / (F.col("accuracy") - F.col("a0"))
    return x.groupBy("method").agg(F.max(at).alias("reuse_rate"))


def compaction_stats(frames_of: DataFrame, active: str, by: list[str], tile: int = 128) -> DataFrame:
    """multiplies, rows, rows per multiply and tile fill when the active tokens of each group are gathered into one multiply."""
    g = frames_of.groupBy(*by).agg(F.sum(active).alias("rows"))
    padded = F.sum(F.ceil(F.col("rows") / tile) * tile)
    return g.where("rows > 0").agg(F.count(F.lit(1)).alias("multiplies"), F.sum("rows").alias("rows"), (F.sum("rows") / F.count(F.lit(1))).alias("rows_per_multiply"), (F.sum("rows") / padded).alias("tile_fill"))


def positions(tokens: DataFrame, videos: int = 4096, epochs: int = 256) -> DataFrame:
    """Rows of (video_id, frame_no, token_no, wavefront) with `position`: their place, from 0, in their wavefront's order by video, frame and token.

    Three levels, so that no task orders a whole wavefront: rows of `epochs` epochs of a video are ranked on their own; counts of such groups are
    added up over `videos` neighbouring videos; and the totals of those over the wavefront.
    """
    x = tokens.withColumns({"_e": F.floor(F.col("frame_no") / F.lit(20 * epochs)), "_s": F.floor(F.col("video_id") / videos)})
    group = ["wavefront", "_s", "video_id", "_e"]
    n = x.groupBy(*group).agg(F.count(F.lit(1)).alias("_n"))
    inner = Window.partitionBy("wavefront", "_s").orderBy("video_id", "_e")
    n = n.withColumn("_a", F.sum("_n").over(inner) - F.col("_n"))
    m = n.groupBy("wavefront", "_s").agg(F.sum("_n").alias("_m"))
    m = m.withColumn("_b", F.sum("_m").over(Window.partitionBy("wavefront").orderBy("_s")) - F.col("_m"))
    start = n.join(m, ["wavefront", "_s"]).select(*group, (F.col("_a") + F.col("_b")).alias("_start"))
    own = F.row_number().over(Window.partitionBy(*group).orderBy("frame_no", "token_no")) - 1
    return x.withColumn("_own", own).join(start, group).select(*tokens.columns, (F.col("_own") + F.col("_start")).cast("bigint").alias("position"))


def flops_parts(done: DataFrame, spec: EncoderSpec, gate: str, calibrator: bool) -> DataFrame:
    """part, flops: what the frames of a gated encode with costs spent on QKV, attention, feed-forward, gate and calibrator, from the tokens that each layer reused."""
    n, d, h = spec.n_tokens, spec.dim, spec.hidden
    last = spec.layers - 1
    x = done.select(F.posexplode("reused").alias("layer", "r"))
    left = n - F.col("r")
    inner = F.col("layer") < last
    parts = {
        "qkv": F.when(inner, 6 * d * d * left).otherwise(0) + F.when(F.col("layer") == 0, 6 * n * d * d).otherwise(0),
        "ffn": 4 * spec.ffn_mult * d * d * left,
        "attention": F.lit(4 * n * n * d + 2 * n * d * d),
        "calibrator": F.col("r") * 2 * h * (d + F.when(inner, 3 * d).otherwise(d)) if calibrator else F.lit(0),
    }
    a = x.agg(*[F.sum(v.cast("double")).alias(k) for k, v in parts.items()])
    gated = done.agg(F.sum("flops").alias("all"))
    y = a.crossJoin(F.broadcast(gated)).withColumn("gate", F.col("all") - F.col("qkv") - F.col("ffn") - F.col("attention") - F.col("calibrator"))
    return y.select(F.inline(F.array(*[F.struct(F.lit(k).alias("part"), F.col(k).alias("flops")) for k in (*parts, "gate")])))


def task_flops(spark: SparkSession, spec: EncoderSpec, tasks: DataFrame) -> DataFrame:
    """task, part, flops, share: encoder and head of query kinds, from (task, frames, head_ops): the head's multiplications and additions."""
    full = spec.layers * (spec.n_tokens * 24 * spec.dim**2 + 4 * spec.n_tokens**2 * spec.dim)
    x = tasks.select("task", F.inline(F.array(F.struct(F.lit("encoder").alias("part"), (F.col("frames") * full).cast("double").alias("flops")), F.struct(F.lit("head").alias("part"), F.col("head_ops").cast("double").alias("flops")))))
    return x.withColumn("share", F.col("flops") / F.sum("flops").over(Window.partitionBy("task")))
