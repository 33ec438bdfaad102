"""Queries over embeddings: retrieval, multiple choice, grounding."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import vector as V
from . import search

#: Queries and choices are stated sets; they are broadcast up to this number of rows.
BROADCAST_ROWS = 100_000


def _side(df: DataFrame) -> DataFrame:
    return F.broadcast(df) if df.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS else df


def in_blocks(queries: DataFrame, key: str, per_block) -> DataFrame:
    """per_block(part) for broadcast parts of a query set, joined again: all queries are taken, however many there are."""
    n = queries.count()
    blocks = max(1, -(-n // (BROADCAST_ROWS // 2)))
    out = None
    for i in range(blocks):
        part = queries if blocks == 1 else queries.where(F.pmod(F.xxhash64(key), F.lit(blocks)) == i)
        x = per_block(F.broadcast(part))
        out = x if out is None else out.unionByName(x)
    return out


def retrieve(queries: DataFrame, clips: DataFrame, k: int = 5) -> DataFrame:
    """query_id, clip_id, score, rank: the k clips of greatest cosine; of equal ones the smaller clip_id."""
    return search.nearest(queries, clips, k)


def recall(top: DataFrame, gold: DataFrame) -> DataFrame:
    """recall: the share of gold (query_id, clip_id) pairs among the retrieved."""
    return gold.join(top.select("query_id", "clip_id", F.lit(1).alias("hit")), ["query_id", "clip_id"], "left").agg((F.sum(F.coalesce("hit", F.lit(0))) / F.count(F.lit(1))).alias("recall"))


def answer(questions: DataFrame, choices: DataFrame) -> DataFrame:
    """query_id, choice_no, score: for each question (query_id, emb) the choice (choice_no, vec) of greatest cosine, the first of equals."""
    x = questions.crossJoin(_side(choices)).select("query_id", "choice_no", V.cosine(F.col("emb"), F.col("vec")).alias("score"))
    return x.groupBy("query_id").agg(F.max(F.struct("score", (-F.col("choice_no")).alias("n"))).alias("m")).select("query_id", (-F.col("m.n")).alias("choice_no"), F.col("m.score").alias("score"))


def ground(scores: DataFrame, threshold: float = 0.5, by: str = "total", digits: int | None = None) -> DataFrame:
    """query_id, lo, hi, total: of (query_id, frame_no, score), the run of frames above the threshold with the greatest total, or peak, the earliest of equals.

    With `digits`, totals are rounded before they are compared, so that equal runs are equal in whatever order their scores were added.
    """
    x = scores.where(F.col("score") >= threshold)
    island = F.col("frame_no") - F.row_number().over(Window.partitionBy("query_id").orderBy("frame_no"))
    total = (F.sum if by == "total" else F.max)("score")
    total = total if digits is None else F.round(total, digits)
    runs = x.withColumn("_i", island).groupBy("query_id", "_i").agg(F.min("frame_no").alias("lo"), F.max("frame_no").alias("hi"), total.alias("total"))
    best = runs.groupBy("query_id").agg(F.max(F.struct("total", (-F.col("lo")).alias("n"), "hi")).alias("m"))
    return best.select("query_id", (-F.col("m.n")).alias("lo"), F.col("m.hi").alias("hi"), F.col("m.total").alias("total"))


def overlap(spans: DataFrame, gold: DataFrame) -> DataFrame:
    """query_id, iou of predicted and gold spans; a missing span has 0."""
    g = gold.select("query_id", F.col("lo").alias("_a"), F.col("hi").alias("_b"))
    x = g.join(spans.select("query_id", "lo", "hi"), "query_id", "left")
    both = F.greatest(F.lit(0), F.least("hi", "_b") - F.greatest("lo", "_a") + 1)
    either = (F.col("hi") - F.col("lo") + 1) + (F.col("_b") - F.col("_a") + 1) - both
    return x.select("query_id", F.when(F.col("lo").isNull(), 0.0).otherwise(both / either).alias("iou"))


def clips(frames: DataFrame, length: int, key: str = "clip_id") -> DataFrame:
    """frames with the number of their clip: `length` frames in a row of a video, numbered over all videos by a struct of video and clip."""
    return frames.withColumn(key, F.struct("video_id", F.floor((F.col("frame_no") - 1) / length).cast("int").alias("clip")))


def count_answer(counts: DataFrame, numeric: list[int]) -> DataFrame:
    """query_id, choice_no, score: for "how many" questions, the numeric choice nearest to an estimated count (query_id, estimate), the smaller of equals."""
    near = F.array(*[F.struct(F.abs(F.col("estimate") - c).alias("d"), F.lit(c).alias("c")) for c in numeric])
    return counts.select("query_id", F.array_min(near)["c"].alias("choice_no"), (-F.array_min(near)["d"]).alias("score"))
