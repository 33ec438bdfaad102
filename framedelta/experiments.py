"""The experiments that run encoders, a query each. Where rows have a `fold`, "train" are the videos that gates and heads learned from."""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import oracles
from .functions import vector as V
from .model import EncoderSpec, ReuseConfig
from .operators import baselines, encode, heads, kernel, measures, search, store, tasks, training
from .plans.reference import plan_frames
from .pretrained import modules
from .sources import frames as S
from .sources.frames import table
from .train import MORPH, PROSE, SHIP, TARGETS, TINY
from .workloads import ACT, ACT_FRAMES, PLAN, PRESETS, WORDS, plan_sql, query, scrolled_sql, ship_sql

FIXED = dict(scheme="sequential", calibrator=False)


def mse(theta: float, **o) -> ReuseConfig:
    return ReuseConfig(gate="mse", theta=theta, **{**FIXED, **o})


def budget(k: int, **o) -> ReuseConfig:
    return ReuseConfig(gate="budget", budget=k, **{**FIXED, **o})


def union(parts) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b), parts)


def encoded(frames: DataFrame, spec: EncoderSpec, way, weights=None) -> DataFrame:
    """EMBEDDINGS by a way: a ReuseConfig, (prune, merge), or None for the unmodified encoder. weights is a name in weights.json or modules."""
    if way is None:
        return encode.full_encode(frames, spec)
    if isinstance(way, tuple):
        return encode.intra_frame_reduce(frames, spec, *way)
    m = modules(weights) if isinstance(weights, str) else weights
    return encode.gated_encode(frames, spec, way, m if way.gate == "learned" else None)


def compared(frames: DataFrame, spec: EncoderSpec, ways: dict, held_out: bool = False) -> DataFrame:
    """method, fold and cosine_to_exact of each way; ways has name: way or [way, weights]. Frames and exact embeddings are made once.

    Tasks compare each frame where they encode it; only sums by method and fold move, and every method reads its own from there. held_out leaves out the other fold before it is encoded.
    """
    if held_out:
        frames = frames.where(~training.is_train())
    fold = F.when(training.is_train(), "train").otherwise("held_out")
    each = []
    for way in ways.values():
        way, weights = way if isinstance(way, list) else (way, None)
        m = modules(weights) if isinstance(weights, str) else weights
        each.append((way, m if way.gate == "learned" else None) if isinstance(way, ReuseConfig) else way)
    x = measures.fidelity(encode.against_exact(frames, spec, each).withColumn("fold", fold), ["way", "fold"])
    w = F.max("way").over(Window.partitionBy("way", "fold"))  # after the sums, so that they are made once for all methods
    x = x.withColumn("_w", w)
    return union(x.where(F.col("_w") == k).drop("way", "_w").withColumn("method", F.lit(name)) for k, name in enumerate(ways))


def show(z: DataFrame, dim: int, *more: str) -> DataFrame:
    """A few numbers that stand for an embedding, as in oracles.shown."""
    e = lambda i: F.round(F.get("emb", F.lit(i - 1)), 5)
    weighted = F.aggregate(F.transform("emb", lambda x, i: x * (i + 1)), F.lit(0.0), lambda a, x: a + x)
    return z.select("video_id", "frame_no", *[e(i).alias(f"e{i}") for i in (1, dim // 2, dim)], F.round(weighted, 5).alias("weighted"), *more)


# ---- the encoder itself --------------------------------------------------------------------------------------------

ACT_TOK = f"{ACT}, tok AS (SELECT user_id AS v, k + 1 AS f, kind AS t, list(v ORDER BY slot) AS raw FROM slots GROUP BY user_id, k, kind)"


@query(f"WITH {ACT_TOK}, {oracles.exact_ctes(TINY)} SELECT v AS video_id, CAST(f AS INT) AS frame_no, {oracles.shown(TINY.dim)} FROM z")
def exact_embedding(spark, sf):
    return show(encode.full_encode(S.activity(spark, sf), TINY), TINY.dim)


def _gated_sql(cfg: ReuseConfig, waves: int) -> str:
    plan = plan_sql(cfg.tail, ACT_FRAMES)
    return f"WITH {ACT_TOK}, pl AS MATERIALIZED (SELECT video_id AS v, frame_no AS f, ftype AS ft, past_ref AS past, future_ref AS future, wavefront AS wave FROM ({plan})), {oracles.gated_ctes(TINY, cfg, modules('activity'), waves)} SELECT z.v AS video_id, CAST(z.f AS INT) AS frame_no, {oracles.shown(TINY.dim)}, round(rate, 5) AS reuse_rate FROM z JOIN reused ON reused.v = z.v AND reused.f = z.f"


@query(_gated_sql(ReuseConfig(), 8))
def gated_embedding(spark, sf):
    """The trained gate and calibrator, bidirectional references, all layers: embeddings and reuse of every frame."""
    z = encode.gated_encode(S.activity(spark, sf), TINY, ReuseConfig(), modules("activity"))
    return show(z.withColumn("reuse_rate", F.round("reuse_rate", 5)), TINY.dim, "reuse_rate")


@query(_gated_sql(ReuseConfig(tail="recompute"), 7))
def gated_embedding_recomputed_tail(spark, sf):
    z = encode.gated_encode(S.activity(spark, sf), TINY, ReuseConfig(tail="recompute"), modules("activity"))
    return show(z.withColumn("reuse_rate", F.round("reuse_rate", 5)), TINY.dim, "reuse_rate")


def _fixed_gate_sql(cfg: ReuseConfig) -> str:
    plan = f"WITH {ACT_FRAMES} SELECT v, f, CASE WHEN p = 0 THEN 'I' ELSE 'P' END AS ft, CASE WHEN p > 0 THEN f - 1 END AS past, CAST(NULL AS BIGINT) AS future, p AS wave FROM ps"
    return f"WITH {ACT_TOK}, pl AS MATERIALIZED ({plan}), {oracles.gated_ctes(TINY, cfg, None, cfg.reset_every)} SELECT z.v AS video_id, CAST(z.f AS INT) AS frame_no, {oracles.shown(TINY.dim)}, round(rate, 5) AS reuse_rate FROM z JOIN reused ON reused.v = z.v AND reused.f = z.f"


@query(_fixed_gate_sql(mse(0.02)))
def mse_gated_embedding(spark, sf):
    """The fixed threshold on the mean squared change, frames in their own order, in all layers: embeddings and reuse of every frame."""
    z = encode.gated_encode(S.activity(spark, sf), TINY, mse(0.02))
    return show(z.withColumn("reuse_rate", F.round("reuse_rate", 5)), TINY.dim, "reuse_rate")


@query(_fixed_gate_sql(budget(2)))
def budget_gated_embedding(spark, sf):
    """The fixed budget: the class token and the two tokens that changed most are computed, the others reused."""
    z = encode.gated_encode(S.activity(spark, sf), TINY, budget(2))
    return show(z.withColumn("reuse_rate", F.round("reuse_rate", 5)), TINY.dim, "reuse_rate")


@query(f"WITH {ACT_TOK}, {oracles.exact_ctes(TINY, prune=1)} SELECT v AS video_id, CAST(f AS INT) AS frame_no, {oracles.shown(TINY.dim)} FROM z")
def pruned_embedding(spark, sf):
    """In-frame reduction by pruning alone: in each layer the token of least class attention goes."""
    return show(encode.intra_frame_reduce(S.activity(spark, sf), TINY, prune=1, merge=0), TINY.dim)


@query(f"""WITH {ACT}, one AS (SELECT user_id, k // 4 AS w, kind, slot, avg(v) AS v FROM slots GROUP BY ALL),
tok AS (SELECT user_id AS v, w AS f, kind AS t, list(v ORDER BY slot) AS raw FROM one GROUP BY user_id, w, kind), {oracles.exact_ctes(TINY)}
SELECT user_id AS video_id, CAST(k + 1 AS INT) AS frame_no, {oracles.shown(TINY.dim)} FROM (SELECT DISTINCT user_id, k FROM slots) s JOIN z ON z.v = s.user_id AND z.f = k // 4""")
def temporal_merge_embedding(spark, sf):
    """Four frames in a row share the embedding of their mean tokens."""
    return show(baselines.temporal_merge(S.activity(spark, sf), TINY, 4), TINY.dim)


@query()
def lookback_references(spark, sf):
    """One, two and three past references in the sequential scheme: what more of them bring."""
    f = S.activity(spark, sf)
    return compared(f, TINY, {f"past {k}": [ReuseConfig("sequential", lookback=k), "activity sequential"] for k in (1, 2, 3)})


@query()
def gate_features(spark, sf):
    """The learned gate without one of its inputs: similarity, importance, reference type, codec hints."""
    ways = {"all": "strc", "no similarity": "trc", "no importance": "src", "no type": "stc", "no hints": "str"}
    return compared(S.activity(spark, sf), TINY, {n: [ReuseConfig(features=x), "activity"] for n, x in ways.items()})


@query()
def own_type_gate(spark, sf):
    """Gates fitted with and without the type of their own frame, on the same bounded sample."""
    f = S.activity(spark, sf)
    g = training.sample_groups(f, TINY, 3, 200)
    fit = lambda own: training.fit_reuse(g, TINY, steps=60, own_type=own)[0]
    return compared(f, TINY, {"reference's type": [ReuseConfig(), fit(False)], "reference's and own type": [ReuseConfig(own_type=True), fit(True)]})


@query()
def distributed_training(spark, sf):
    """step, loss, cosine, reuse and temperature of a short fit over all training groups, a quarter of them in each step."""
    _, log = training.fit_reuse_distributed(S.activity(spark, sf), TINY, steps=20, share=0.25)
    return spark.createDataFrame([(int(a), *map(float, x)) for a, *x in log], "step int, loss double, cosine double, reuse double, temperature double")


# ---- trade-offs -----------------------------------------------------------------------------------------------------


@query()
def activity_tradeoff(spark, sf, **only):
    """Learned gate, fixed gates, and in-frame reduction at several settings."""
    m: dict = {f"learned {s:+g}": [ReuseConfig(shift=s), "activity"] for s in (-2, -1, 0, 1, 2)}
    m |= {f"mse {t}": mse(t) for t in (0.005, 0.02, 0.1, 0.3)} | {f"budget {k}": budget(k) for k in (1, 2, 3)}
    m |= {"prune+merge": (1, 1), "prune": (1, 0), "merge": (0, 1)}
    return compared(S.activity(spark, sf), TINY, m, **only)


@query()
def morph_tradeoff(spark, sf):
    m: dict = {f"learned {s:+g}": [ReuseConfig(shift=s), "morph"] for s in (-1, 0, 1)}
    m |= {f"{s} mse {t}": mse(t, scheme=s) for s in ("sequential", "reordered") for t in (0.005, 0.02)}
    return compared(S.morph(spark, sf), MORPH, m | {"budget 2": budget(2), "budget 4": budget(4), "prune+merge": (1, 1)})


@query()
def prose_tradeoff(spark, sf):
    m: dict = {"learned": [ReuseConfig(), "prose"], "mse 0.1": mse(0.1), "budget 3": budget(3), "prune+merge": (1, 1), "prune": (2, 0), "merge": (0, 2)}
    return compared(S.prose(spark, sf), PROSE, m)


@query()
def talk_tradeoff(spark, sf):
    return compared(S.talk(spark, sf), PROSE, {"learned": [ReuseConfig(), "talk"], "mse 0.5": mse(0.5), "budget 5": budget(5), "prune+merge": (1, 1)})


@query()
def shipping_tradeoff(spark, sf, **only):
    m: dict = {f"learned {s:+g}": [ReuseConfig(shift=s), "ship"] for s in (-1, 0, 1)}
    return compared(S.shipping(spark, sf), SHIP, m | {"mse 0.1": mse(0.1), "mse 0.5": mse(0.5), "budget 3": budget(3), "budget 3, last fresh": budget(3, reference="last_fresh")}, **only)


def rates_for(frames: DataFrame, spec: EncoderSpec, flops_x: float) -> tuple:
    """Prune and merge counts of each layer, fitted on a bounded sample of training frames."""
    g = training.sample_groups(frames, spec, 1, 100)
    return baselines.fit_rates(g.reshape(-1, *g.shape[2:]), spec, flops_x)


@query()
def reduction_rates(spark, sf):
    """The in-frame baseline with fitted rates against rates set by hand, at about the same cost."""
    f = S.morph(spark, sf)
    return compared(f, MORPH, {"fitted": rates_for(f, MORPH, 1.6), "prune+merge": (1, 1), "prune": (2, 0), "merge": (0, 2)})


# ---- ablations at equal reuse -----------------------------------------------------------------------------------------


def at_equal_reuse(frames: DataFrame, spec: EncoderSpec, ways: dict, rho: float) -> dict:
    """ways moved to the reuse rate rho on a bounded sample of whole epochs of this table's training videos."""
    epochs = training.sample_epochs(frames, spec)
    out = {}
    for name, (cfg, weights) in ways.items():
        m = modules(weights) if isinstance(weights, str) else weights
        out[name] = [training.at_reuse(epochs, spec, cfg, m, rho), m]
    return out


@query()
def design_ablation(spark, sf):
    """Gate alone, then with frames in the other order, then trained on groups, then with the calibrator, all at 60 % reuse, against the fixed gates."""
    f = S.activity(spark, sf)
    ways = {
        "gate": [ReuseConfig("sequential", calibrator=False), "activity gate"],
        "gate, order": [ReuseConfig(calibrator=False), "activity gate, order"],
        "gate, order, grouping": [ReuseConfig(calibrator=False), "activity gate, order, grouping"],
        "gate, order, grouping, calibrator": [ReuseConfig(), "activity"],
        "mse": [mse(0.1), None],
    }
    return compared(f, TINY, at_equal_reuse(f, TINY, ways, 0.6) | {"budget": budget(2)})


@query()
def shipping_design_ablation(spark, sf):
    """The ladder on the drifting fixture with its one set of weights, at 50 % reuse."""
    f = S.shipping(spark, sf)
    ways = {"gate": [ReuseConfig("sequential", calibrator=False), "ship"], "gate, order": [ReuseConfig(calibrator=False), "ship"], "gate, order, calibrator": [ReuseConfig(), "ship"], "mse": [mse(0.1), None]}
    return compared(f, SHIP, at_equal_reuse(f, SHIP, ways, 0.5) | {"budget": budget(3)})


@query()
def grouping_ablation(spark, sf):
    """Weights trained frame by frame, on sequential groups and on groups of one to four segments; all encode in the reordered scheme at 60 % reuse."""
    names = {"frame-wise": "activity frame-wise", "sequential": "activity sequential", "1 segment": "activity g1", "2 segments": "activity g2", "3 segments": "activity", "4 segments": "activity g4"}
    f = S.activity(spark, sf)
    return compared(f, TINY, at_equal_reuse(f, TINY, {k: [ReuseConfig(), v] for k, v in names.items()}, 0.6))


@query()
def target_sweep(spark, sf):
    """Weights trained for several reuse targets: the trade-off that the target draws."""
    return compared(S.activity(spark, sf), TINY, {f"target {r}": [ReuseConfig(), f"activity target {r}"] for r in TARGETS})


@query()
def flops_breakdown_fixed_reuse(spark, sf):
    """method, part, flops and their share of the exact encoder's, with gates set for 61 % reuse."""
    f = S.activity(spark, sf)
    ways = at_equal_reuse(f, TINY, {"learned": [ReuseConfig(), "activity"], "mse": [mse(0.1), None]}, 0.61) | {"budget": [budget(2), None]}
    out = []
    for name, (cfg, m) in ways.items():
        z = encode.gated_encode(f, TINY, cfg, m if cfg.gate == "learned" else None, with_costs=True).select("reused", "flops", "reuse_rate")
        z = store.written(z, "costs")
        total = z.agg((F.count(F.lit(1)) * kernel.flops_exact(TINY)).alias("full"), F.avg("reuse_rate").alias("reuse_rate"))
        x = measures.flops_parts(z, TINY, cfg.gate, cfg.calibrator and m is not None).crossJoin(F.broadcast(total))
        out.append(x.select(F.lit(name).alias("method"), "part", "flops", (F.col("flops") / F.col("full")).alias("share"), "reuse_rate"))
    return union(out)


@query()
def reuse_at_equal_accuracy(spark, sf):
    """The reuse rate of each method at a mean cosine of 0.995 and 0.99 on held-out videos, between measured points."""
    m: dict = {("learned", f"{s:+g}"): [ReuseConfig(shift=s), "activity"] for s in (-4, -2, 0, 2, 4, 8)}
    m |= {("mse", str(t)): mse(t) for t in (0.005, 0.02, 0.1, 0.3, 1.0)} | {("budget", str(k)): budget(k) for k in (1, 2, 3, 4)}
    x = compared(S.activity(spark, sf), TINY, {"|".join(k): v for k, v in m.items()}, held_out=True)
    x = store.written(x.select(F.split("method", r"\|")[0].alias("method"), F.col("cos_mean").alias("accuracy"), "reuse_rate"), "points")
    return union(measures.reuse_at_accuracy(x, a).withColumn("accuracy", F.lit(a)) for a in (0.99, 0.995))


@query()
def adaptivity_series(spark, sf):
    """Reuse and cosine by frame and frame type, over time: how methods follow what happens and how a full frame resets errors."""
    f = S.activity(spark, sf)
    kind = plan_frames(f.select("video_id", "frame_no")).select("video_id", "frame_no", "ftype")
    exact = encode.full_encode(f, TINY)
    out = []
    for name, (cfg, w) in {"learned": (ReuseConfig(), "activity"), "budget": (budget(2), None)}.items():
        got = encoded(f, TINY, cfg, w).join(kind, ["video_id", "frame_no"])
        out.append(measures.cosine_to_exact(got, exact, ["frame_no", "ftype"]).withColumn("method", F.lit(name)))
    return union(out)


@query()
def burst_series(spark, sf):
    """The busiest user's frames one by one: raw change, reuse and cosine of the learned and the fixed-budget gate."""
    f = S.activity(spark, sf)
    top = table(spark, sf, "events").groupBy(F.col("user_id").alias("video_id")).agg(F.max("value").alias("m")).orderBy(F.desc("m"), "video_id").limit(1)
    f = f.join(F.broadcast(top.select("video_id")), "video_id", "left_semi")
    w = Window.partitionBy("video_id").orderBy("frame_no")  # one video of bounded length
    moved = f.select("video_id", "frame_no", V.mse(F.col("tokens"), F.lag("tokens").over(w)).alias("change"))
    exact = encode.full_encode(f, TINY).select("video_id", "frame_no", F.col("emb").alias("z"))
    out = []
    for name, (cfg, weights) in {"learned": (ReuseConfig(), "activity"), "budget": (budget(2), None)}.items():
        x = encoded(f, TINY, cfg, weights).join(exact, ["video_id", "frame_no"]).select("video_id", "frame_no", "reuse_rate", V.cosine(F.col("emb"), F.col("z")).alias("cosine"))
        out.append(x.withColumn("method", F.lit(name)))
    return union(out).join(moved, ["video_id", "frame_no"])


@query()
def reset_sweep(spark, sf):
    """Reset periods; the last is longer than any video, so nothing is reset."""
    return compared(S.activity(spark, sf), TINY, {f"reset {k}": [ReuseConfig(reset_every=k), "activity"] for k in (4, 8, 12, 20, 40, 4000)})


@query()
def schedule_costs(spark, sf):
    """Multiplies, rows and peak cache of each schedule and compaction; the embeddings are the same."""
    ways = (("frame", "none", False), ("frame", "frame", False), ("frame", "frame", True), ("layer", "none", False), ("layer", "frame", True), ("layer", "batch", False), ("layer", "batch", True))
    cfgs = [ReuseConfig(schedule=schedule, compaction=compaction, free_cache=free, batch_epochs=16) for schedule, compaction, free in ways]
    x = encode.schedule_costs(S.activity(spark, sf), TINY, cfgs, modules("activity"))
    x = x.groupBy("way").agg(F.sum("multiplies").alias("multiplies"), F.sum("rows").alias("rows"), F.max("peak").alias("peak_bytes"), (F.sum("reuse") / F.sum("frames")).alias("reuse_rate"))
    names = F.array(*[F.lit(f"{schedule}, {compaction}, {'freed' if free else 'kept'}") for schedule, compaction, free in ways])
    return x.select(F.get(names, F.col("way")).alias("method"), "multiplies", "rows", "peak_bytes", "reuse_rate")


# ---- query tasks on embeddings -----------------------------------------------------------------------------------------

#: Frames at least so similar to a question are part of its span.
GROUND_LEAST = 0.75
METHODS = {"exact": None, "learned": ReuseConfig(), "mse": mse(0.02), "budget": budget(2), "prune+merge": (1, 1)}


def each_once(frames: DataFrame, spec: EncoderSpec, weights: str) -> dict[str, DataFrame]:
    """Every method's embeddings, encoded once and written; costs and answers are read from there. The frames are made once, too."""
    frames = store.written(frames, "frames")
    return {n: store.written(encoded(frames, spec, way, weights), "embeddings") for n, way in METHODS.items()}


def cost(z: DataFrame) -> DataFrame:
    return z.agg(F.avg("reuse_rate").alias("reuse_rate"), F.sum("flops").alias("flops"))


@query()
def retrieval_tradeoff(spark, sf):
    """method, accuracy (recall at 5), reuse_rate, flops: a clip is the eight frames after a key vector, a query the exact embedding of its third frame; every clip has one."""
    ways = each_once(S.morph(spark, sf), MORPH, "morph")
    no = F.floor((F.col("frame_no") - 1) / 8)
    ways = {n: z.withColumn("clip_id", F.struct("video_id", no.alias("clip"))) for n, z in ways.items()}
    q = ways["exact"].where("(frame_no - 1) % 8 = 2").select(F.col("clip_id").alias("query_id"), F.col("emb").alias("vec"))
    gold = q.select("query_id", F.col("query_id").alias("clip_id"))
    out = []
    for name, z in ways.items():
        top = tasks.retrieve(q, V.mean_pool(z, ["clip_id"]), 5)
        out.append(tasks.recall(top, gold).withColumnRenamed("recall", "accuracy").crossJoin(cost(z)).withColumn("method", F.lit(name)))
    return union(out)


def activity_heads(frames: DataFrame, exact: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(weights (dim + 1, types), (mean, deviation) of each type): linear heads from exact embeddings to what each event type holds in the last 72 hours."""
    y = F.transform(F.sequence(F.lit(1), F.lit(len(S.EVENT_TYPES))), lambda i: F.aggregate(F.slice("tokens", i * S.RING + 1, S.RING), F.lit(0.0), lambda a, x: a + x))
    rows = frames.where(training.is_train()).select("video_id", "frame_no", y.alias("y")).join(exact.select("video_id", "frame_no", "emb"), ["video_id", "frame_no"])
    return heads.fit(rows, sample=4000)


@query()
def qa_tradeoff(spark, sf):
    """method, accuracy, reuse_rate, flops: which of five event types is strongest in a ten-day clip of a held-out user; a linear head reads the pooled embedding."""
    f = S.activity(spark, sf)
    ways = each_once(f, TINY, "activity")
    w, scale = activity_heads(f, ways["exact"])
    held = ~training.is_train()
    pool = lambda x, c: V.mean_pool(tasks.clips(x.where(held), 40), ["clip_id"], c)
    sums = pool(f, "tokens").select("clip_id", F.transform(F.sequence(F.lit(1), F.lit(len(S.EVENT_TYPES))), lambda i: F.aggregate(F.slice("tokens", i * S.RING + 1, S.RING), F.lit(0.0), lambda a, x: a + x)).alias("y"))
    gold = sums.select("clip_id", heads.strongest(heads.standard(F.col("y"), scale)).alias("gold"))
    out = []
    for name, z in ways.items():
        a = pool(z, "emb").select("clip_id", heads.strongest(heads.standard(heads.read(F.col("emb"), w), scale)).alias("choice_no")).join(gold, "clip_id")
        x = a.agg(F.avg((F.col("choice_no") == F.col("gold")).cast("double")).alias("accuracy"), F.count(F.lit(1)).alias("questions"))
        out.append(x.crossJoin(cost(z)).withColumn("method", F.lit(name)))
    return union(out)


@query()
def grounding_tradeoff(spark, sf):
    """method, accuracy (right video and an overlap of at least one half), mean_iou, reuse_rate, flops: in which of all videos is a scene, and when?

    The question is the exact embedding of the fourth frame of a scene (the eight frames from one key vector to the next); every scene has one. The answer is the run of frames
    above the threshold with the highest peak. All embeddings are taken from the mean of the exact ones.
    """
    ways = each_once(S.morph(spark, sf), MORPH, "morph")
    mean = V.mean_pool(ways["exact"].withColumn("one", F.lit(1)), ["one"]).first()
    middle = [float(x) for x in mean["emb"]] if mean else None
    no = F.floor((F.col("frame_no") - 1) / 8)
    q = ways["exact"].where("(frame_no - 1) % 8 = 3").select(F.struct("video_id", no.cast("int").alias("clip")).alias("query_id"), F.col("emb").alias("vec"))
    gold = store.written(q.select("query_id", (F.col("query_id.clip") * 8 + 1).alias("lo"), (F.col("query_id.clip") * 8 + 8).alias("hi")), "gold")
    out = []
    for name, z in ways.items():
        best = store.written(search.runs_by_peak(q, z, GROUND_LEAST, middle), "spans")
        x = tasks.overlap(best, gold).join(best.select("query_id", "video_id"), "query_id", "left")
        right = (F.col("video_id") == F.col("query_id.video_id")) & (F.col("iou") >= 0.5)
        a = x.agg(F.avg(F.coalesce(right, F.lit(False)).cast("double")).alias("accuracy"), F.avg(F.when(F.col("video_id") == F.col("query_id.video_id"), F.col("iou")).otherwise(0.0)).alias("mean_iou"), F.count(F.lit(1)).alias("questions"))
        out.append(a.crossJoin(cost(z)).withColumn("method", F.lit(name)))
    return union(out)


@query()
def talk_qa_tradeoff(spark, sf):
    """method, accuracy, reuse_rate, flops: from which of four replies are these words? The question is every second word of a reply, encoded exactly."""
    f = S.talk(spark, sf)
    ways = each_once(f, PROSE, "talk")
    w = Window.partitionBy("conv_id").orderBy("turn")
    t = table(spark, sf, "conversations").where("conv_id is not null and text is not null").select(F.col("conv_id").cast("bigint").alias("video_id"), F.row_number().over(w).alias("frame_no"), "role", F.split("text", " ").alias("w"))
    r = t.where("role = 'assistant'").select("video_id", "frame_no", F.filter("w", lambda x, i: i % 2 == 0).alias("w"))
    buckets = max(1, r.count() // 10_000)
    b = F.pmod(F.xxhash64("video_id", "frame_no"), F.lit(buckets))
    order = Window.partitionBy("b").orderBy("video_id", "frame_no")
    ranked = store.written(r.withColumn("b", b).withColumns({"rank": F.row_number().over(order) - 1, "size": F.count(F.lit(1)).over(Window.partitionBy("b"))}), "questions")
    blocks = S.blocks_as_tokens(S.hashed_words(F.array_join("w", " "), 16), 16)
    asked = encode.full_encode(ranked.select("video_id", "frame_no", blocks.alias("tokens")), PROSE).select(F.col("video_id").alias("qv"), F.col("frame_no").alias("qf"), F.col("emb").alias("vec"))
    offered = ranked.select(F.col("video_id").alias("qv"), F.col("frame_no").alias("qf"), "b", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(0), F.lit(3)), lambda i: F.pmod(F.col("rank") + i, F.col("size"))))).alias("rank"))
    pairs = offered.join(ranked.select("b", "rank", "video_id", "frame_no"), ["b", "rank"]).join(asked, ["qv", "qf"])
    pairs = store.written(pairs.select("qv", "qf", "vec", "video_id", "frame_no"), "choices")
    out = []
    for name, z in ways.items():
        s = pairs.join(z.select("video_id", "frame_no", "emb"), ["video_id", "frame_no"]).select("qv", "qf", "video_id", "frame_no", V.cosine(F.col("vec"), F.col("emb")).alias("s"))
        best = s.groupBy("qv", "qf").agg(F.max_by(F.struct("video_id", "frame_no"), F.struct("s", -F.col("video_id"), -F.col("frame_no"))).alias("a"))
        x = best.agg(F.avg(((F.col("a.video_id") == F.col("qv")) & (F.col("a.frame_no") == F.col("qf"))).cast("double")).alias("accuracy"), F.count(F.lit(1)).alias("questions"))
        out.append(x.crossJoin(cost(z)).withColumn("method", F.lit(name)))
    return union(out)


@query()
def prose_retrieval_tradeoff(spark, sf):
    """method, accuracy (recall at 5), reuse_rate, flops: the documents that hold a benchmark passage, found by the nearest of their frames."""
    f = S.prose(spark, sf)
    ways = each_once(f, PROSE, "prose")
    b = table(spark, sf, "benchmark").where("text is not null and item_id is not null").select(F.col("item_id").cast("bigint").alias("video_id"), "text")
    q = encode.full_encode(S.scrolled(b, S.hashed_words(F.col("text"), 16)), PROSE).where("frame_no = 1").select(F.col("video_id").alias("query_id"), F.col("emb").alias("vec"))
    d = table(spark, sf, "documents").where("text is not null").select(F.col("doc_id").cast("bigint").alias("clip_id"), "text")
    gold = search.holding(b.select(F.col("video_id").alias("query_id"), F.col("text").alias("passage")), d)
    gold = store.written(gold, "gold")
    out = []
    for name, z in ways.items():
        top = search.nearest(q, z.select(F.col("video_id").alias("clip_id"), "emb"), 5, grouped=True)
        out.append(tasks.recall(top, gold).withColumnRenamed("recall", "accuracy").crossJoin(cost(z)).withColumn("method", F.lit(name)))
    return union(out)


@query("""
WITH n AS (SELECT (SELECT count(*) FROM (SELECT label, row_number() OVER (PARTITION BY label ORDER BY vec_id DESC) AS r FROM embeddings) WHERE r > 1) * 8 AS morph,
  (SELECT count(*) FROM conversations WHERE conv_id IS NOT NULL AND text IS NOT NULL) AS talk, (SELECT count(DISTINCT user_id) FROM events) AS users,
  (SELECT CAST(floor(epoch(max(ts) - date_trunc('day', min(ts))::TIMESTAMP) / 21600) AS INT) + 1 FROM events) AS ticks,
  (SELECT count(*) FROM conversations WHERE conv_id IS NOT NULL AND text IS NOT NULL AND role = 'assistant') AS replies),
t AS (SELECT 'retrieval' AS task, morph AS frames, CAST(morph AS DOUBLE) * 1024 + CAST(morph // 8 AS DOUBLE) * (morph // 8) * 2 * 1024 AS ops FROM n
  UNION ALL SELECT 'multiple choice', talk, CAST(replies AS DOUBLE) * 4 * 2 * 1024 FROM n
  UNION ALL SELECT 'grounding', users * ticks, CAST(users * ticks AS DOUBLE) * 5 * 2 * 1024 FROM n),
p AS (SELECT task, unnest(['encoder', 'head']) AS part, unnest([frames * 24::DOUBLE * (257::DOUBLE * 24 * 1024 * 1024 + 4::DOUBLE * 257 * 257 * 1024), ops]) AS flops FROM t)
SELECT task, part, flops, flops / sum(flops) OVER (PARTITION BY task) AS share FROM p""")
def task_flops_share(spark, sf):
    """What the encoder is of a query's work, for three query kinds at the tables' numbers of frames with the large encoder."""
    k = S.morph(spark, sf).count()
    turns = table(spark, sf, "conversations").where("conv_id is not null and text is not null")
    t, replies = turns.count(), turns.where("role = 'assistant'").count()
    e = table(spark, sf, "events").where("user_id is not null and ts is not null")
    ticks = e.select("user_id").distinct().count() * (S.ticks_of(e).first()["last"] + 1)
    d = PRESETS["large"].dim
    rows = [("retrieval", k, float(k) * d + float(k // 8) * (k // 8) * 2 * d), ("multiple choice", t, float(replies) * 4 * 2 * d), ("grounding", ticks, float(ticks) * 5 * 2 * d)]
    return measures.task_flops(spark, PRESETS["large"], spark.createDataFrame(rows, "task string, frames bigint, head_ops double"))


# ---- filters, strata and copies -----------------------------------------------------------------------------------------

REGION = "rl AS (SELECT lineitem.* FROM lineitem JOIN supplier ON s_suppkey = l_suppkey JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey WHERE r_name IN ('ASIA', 'EUROPE'))"


@query(f"""WITH {REGION}, {ship_sql("rl")}, tok AS (SELECT l_suppkey AS v, n AS f, t, list(v ORDER BY s) AS raw FROM slots GROUP BY l_suppkey, n, t), {oracles.exact_ctes(SHIP)},
pool AS (SELECT v, list(m ORDER BY i) AS e FROM (SELECT v, i, avg(e[i]) AS m FROM z, range(1, {SHIP.dim + 1}) r(i) GROUP BY v, i) GROUP BY v),
sc AS (SELECT a.v AS q, b.v AS c, round(list_dot_product(a.e, b.e) / sqrt(list_dot_product(a.e, a.e) * list_dot_product(b.e, b.e)), 7) AS s FROM pool a, pool b WHERE a.v % 20 = 0),
rk AS (SELECT *, row_number() OVER (PARTITION BY q ORDER BY s DESC, c) AS n FROM sc)
SELECT q AS query_id, c AS clip_id, CAST(n AS INT) AS rank, round(s, 5) AS score FROM rk WHERE n <= 5""")
def filtered_retrieval(spark, sf):
    """Suppliers of two regions, nearest by pooled embeddings; the region decides before a frame is made."""
    r = table(spark, sf, "region").where(F.col("r_name").isin("ASIA", "EUROPE"))
    n = table(spark, sf, "nation").join(r, F.col("n_regionkey") == F.col("r_regionkey"))
    s = table(spark, sf, "supplier").join(n, F.col("s_nationkey") == F.col("n_nationkey")).select(F.col("s_suppkey").alias("l_suppkey"))
    frames = S.shipping_of(table(spark, sf, "lineitem").join(s, "l_suppkey", "left_semi"))
    z = store.written(V.mean_pool(encode.full_encode(frames, SHIP), ["video_id"]).withColumnRenamed("video_id", "clip_id"), "pooled")
    q = z.where("clip_id % 20 = 0").select(F.col("clip_id").alias("query_id"), F.col("emb").alias("vec"))
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "clip_id")

    def best(part):
        x = z.crossJoin(part).select("query_id", "clip_id", F.round(V.cosine(F.col("vec"), F.col("emb")), 7).alias("score"))
        return x.withColumn("rank", F.row_number().over(w)).where("rank <= 5")

    return tasks.in_blocks(q, "query_id", best).select("query_id", "clip_id", "rank", F.round("score", 5).alias("score"))


@query()
def accuracy_cube(spark, sf):
    """Fidelity and reuse of the learned gate on documents by language, quality and toxicity, and all of their margins."""
    f = S.prose(spark, sf)
    z = encode.full_encode(f, PROSE).select("video_id", "frame_no", F.col("emb").alias("z"))
    x = encoded(f, PROSE, ReuseConfig(), "prose").join(z, ["video_id", "frame_no"])
    x = x.groupBy(F.col("video_id").alias("doc_id")).agg(F.avg(V.cosine(F.col("emb"), F.col("z"))).alias("cosine"), F.avg("reuse_rate").alias("reuse_rate"), F.count(F.lit(1)).alias("frames"))
    d = table(spark, sf, "documents").select("doc_id", "lang").join(table(spark, sf, "labels").select("doc_id", "quality", "toxic"), "doc_id").join(x, "doc_id")
    return d.cube("lang", "quality", "toxic").agg(F.grouping_id().alias("gid"), F.count(F.lit(1)).alias("docs"), F.sum("frames").alias("frames"), F.avg("cosine").alias("cosine"), F.avg("reuse_rate").alias("reuse_rate"))


@query(f"""WITH {scrolled_sql("SELECT min(doc_id) AS doc_id, any_value(w) AS w FROM (" + WORDS.replace("SELECT doc_id,", "SELECT doc_id, text,") + ") GROUP BY text", 8)}, tok AS (SELECT doc_id AS v, f, t, list(v ORDER BY b) AS raw FROM slots GROUP BY doc_id, f, t), {oracles.exact_ctes(PROSE)},
pool AS (SELECT v, count(*) AS frames, avg(e[1]) AS e1, avg(e[16]) AS e16 FROM z GROUP BY v),
one AS (SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS content FROM documents WHERE text IS NOT NULL)
SELECT doc_id AS video_id, content, doc_id = content AS encoded, frames, round(e1, 5) + 0 AS e1, round(e16, 5) + 0 AS e16 FROM one JOIN pool ON v = content""")
def dedup_encode(spark, sf):
    """Equal texts are encoded once: every document with the document that was encoded for it, and a few numbers of the pooled embedding."""
    d = table(spark, sf, "documents").where("text is not null").select(F.col("doc_id").cast("bigint").alias("video_id"), "text", F.sha2("text", 256).alias("sha"))
    first = store.written(d.groupBy("sha").agg(F.min("video_id").alias("content")), "contents")
    one = d.join(first.select(F.col("content").alias("video_id")), "video_id", "left_semi").select("video_id", "text")
    z = encode.full_encode(S.scrolled(one, S.hashed_words(F.col("text"), 16)), PROSE)
    p = z.groupBy(F.col("video_id").alias("content")).agg(F.count(F.lit(1)).alias("frames"), F.round(F.avg(F.get("emb", F.lit(0))), 5).alias("e1"), F.round(F.avg(F.get("emb", F.lit(15))), 5).alias("e16"))
    every = d.select("video_id", "sha").join(first, "sha").select("video_id", "content", (F.col("video_id") == F.col("content")).alias("encoded"))
    return every.join(p, "content").select("video_id", "content", "encoded", "frames", "e1", "e16")


@query()
def map_agreement(spark, sf):
    """Layer-wise reuse decisions that the learned gate and the fixed threshold share, and those that only one of them makes."""
    f = S.activity(spark, sf)
    both = []
    for cfg, w in ((ReuseConfig(), "activity"), (mse(0.1, scheme="reordered"), None)):
        z = encode.gated_encode(f, TINY, cfg, modules(w) if w else None, with_costs=True).select("video_id", "frame_no", F.posexplode("reused").alias("layer", "n"))
        both.append(store.written(z.where("n > 0"), "maps"))
    a, b = both
    parts = {"both": a.intersect(b), "learned only": a.exceptAll(b), "mse only": b.exceptAll(a)}
    return union(x.groupBy("layer").agg(F.count(F.lit(1)).alias("frames"), F.sum("n").alias("tokens")).withColumn("who", F.lit(k)) for k, x in parts.items())


@query()
def method_matrix(spark, sf):
    """Held-out cosine of each method on each fixture, fixtures as columns."""
    x = union(fn(spark, sf, held_out=True).select(F.lit(n).alias("fixture"), F.regexp_extract("method", "^[a-z+]+", 0).alias("kind"), "cos_mean") for n, fn in (("activity", activity_tradeoff), ("shipping", shipping_tradeoff)))
    return x.groupBy("kind").pivot("fixture", ["activity", "shipping"]).agg(F.max("cos_mean"))


@query()
def reuse_rollup(spark, sf):
    """Reuse by method, frame type and position, with subtotals."""
    f = S.activity(spark, sf)
    kind = plan_frames(f.select("video_id", "frame_no")).select(*PLAN)
    x = union(encoded(f, TINY, cfg, w).select("video_id", "frame_no", "reuse_rate", F.lit(n).alias("method")) for n, cfg, w in (("learned", ReuseConfig(), "activity"), ("mse", mse(0.1, scheme="reordered"), None)))
    return x.join(kind, ["video_id", "frame_no"]).rollup("method", "ftype", "segment_no").agg(F.grouping_id().alias("gid"), F.count(F.lit(1)).alias("frames"), F.avg("reuse_rate").alias("reuse_rate"))


# ---- other ways to save work ---------------------------------------------------------------------------------------------


@query()
def temporal_merge(spark, sf):
    f = S.activity(spark, sf)
    return measures.cosine_to_exact(baselines.temporal_merge(f, TINY, 4), encode.full_encode(f, TINY))


def _vectors(spark, sf) -> DataFrame:
    return table(spark, sf, "embeddings").where("embedding is not null").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("emb"))


@query()
def cluster_index(spark, sf):
    """Every 20th vector's five nearest through the index: the members behind its nearest representatives."""
    e = _vectors(spark, sf)
    return baselines.cluster_search(e, e.where("id % 20 = 0").select(F.col("id").alias("query_id"), F.col("emb").alias("vec")))


@query()
def cluster_index_recall(spark, sf):
    """Recall of cluster_index against the exact search."""
    e = _vectors(spark, sf)
    q = e.where("id % 20 = 0").select(F.col("id").alias("query_id"), F.col("emb").alias("vec"))
    gold = tasks.retrieve(q, e.withColumnRenamed("id", "clip_id"), 5).select("query_id", "clip_id")
    return tasks.recall(cluster_index(spark, sf), gold)


@query()
def proxy_cascade(spark, sf):
    """Is a vector of the upper five labels? A cheap proxy where it is sure, the exact label elsewhere."""
    e = table(spark, sf, "embeddings").where("label is not null and embedding is not null").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("emb"), (F.col("label") >= 5).cast("int").alias("label"), (F.col("vec_id") % 5 < 3).alias("is_train"))
    return baselines.proxy_cascade(e, e.select("id", F.col("label").alias("answer")))


@query()
def frame_search(spark, sf):
    """Every 20th frame as a query against all frames."""
    z = encode.full_encode(S.morph(spark, sf), MORPH)
    q = z.where("frame_no % 20 = 0").select((F.col("video_id") * 1_000_000 + F.col("frame_no")).alias("query_id"), F.col("emb").alias("vec"))
    return baselines.frame_search(q, z)


@query("""WITH n AS (SELECT count(*) * 8 AS n FROM (SELECT row_number() OVER (PARTITION BY label ORDER BY vec_id DESC) AS r FROM embeddings WHERE label IS NOT NULL AND embedding IS NOT NULL) WHERE r > 1)
SELECT r AS request, CASE WHEN r = 1 THEN n ELSE 0 END AS encoded FROM n, (VALUES (1), (2)) t(r)""")
def cache_hits(spark, sf):
    """Frames that had to be encoded by a first and a second request for the same videos."""
    s = store.EmbeddingStore(spark, store.new_path(spark, "store"))
    f = S.morph(spark, sf)
    n = [s.get_or_encode(f, "morph", "tiny", MORPH, ReuseConfig(gate="mse", calibrator=False))[1] for _ in range(2)]
    return spark.createDataFrame([(i + 1, x) for i, x in enumerate(n)], "request int, encoded bigint")


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """For each video of the activity frames: mean cosine to the exact encoder, reuse rate and FLOPs saved."""
    f = S.activity(spark, sf)
    got = encode.gated_encode(f, TINY, ReuseConfig(), modules("activity"))
    return measures.cosine_to_exact(got, encode.full_encode(f, TINY), ["video_id"])
