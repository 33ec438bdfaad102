"""Reference plans: in which order frames are encoded and which frames each may reuse.

All of it is arithmetic on frame_no; only the tail rule needs the number of frames of the video. Epochs (from one fully computed
frame to the next) are independent given the halo, so they are the unit of work.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SCHEMES, TAILS = ("sequential", "reordered"), ("chain", "short_anchor", "recompute")


def plan_frames(frames: DataFrame, scheme: str = "reordered", reset_every: int = 20, tail: str = "chain", lookback: int = 1, payload: tuple[str, ...] = ()) -> DataFrame:
    """video_id, frame_no, epoch_no, segment_no, ftype, past_ref, future_ref, wavefront, exec_order, is_halo; with lookback > 1 also refs; and the payload columns of frames."""
    if scheme not in SCHEMES or tail not in TAILS:
        raise ValueError("unknown scheme or tail rule")
    if scheme == "reordered" and reset_every % 4:
        raise ValueError("reset_every must be a multiple of 4")
    base = frames.select("video_id", "frame_no", *payload)
    f = F.col("frame_no")
    pos = F.pmod(f - 1, F.lit(reset_every))
    epoch = F.floor((f - 1) / reset_every).cast("int")
    none = F.lit(None).cast("int")
    if scheme == "sequential":
        first = pos == 0
        out = base.select("video_id", "frame_no", epoch.alias("epoch_no"), F.floor(pos / 4).cast("int").alias("segment_no"), F.when(first, "I").otherwise("P").alias("ftype"), F.when(first, none).otherwise(f - 1).alias("past_ref"), none.alias("future_ref"), pos.alias("wavefront"), pos.alias("exec_order"), F.lit(False).alias("is_halo"), *payload)
        if lookback > 1:
            start = f - pos
            out = out.withColumn("refs", F.filter(F.sequence(f - lookback, f - 1), lambda r: r >= start))
        return out
    n = frames.groupBy("video_id").agg(F.max("frame_no").alias("n"))  # a row for each video
    base = base.join(n, "video_id")
    q, k = F.pmod(pos, F.lit(4)), F.floor(pos / 4).cast("int")
    closed = f - q + 4 <= F.col("n")
    last_seg = pos - q + 4 == reset_every
    after = F.when(last_seg, 0).otherwise(k + 1)  # the wavefront of the closing anchor
    b2 = 1 + F.greatest(k, after)
    m = F.col("n") - (f - q)  # frames after the anchor in an open segment
    past, future, kind, wave = none, none, F.lit("I"), F.lit(0)
    if tail == "chain":
        past, kind, wave = f - 1, F.lit("P"), k + q
    elif tail == "short_anchor":
        end = q == m
        past = F.when(end, f - q).when(q == 1, f - 1).otherwise(f - 2)
        future = F.when(end, none).otherwise(f + 1)
        kind = F.when(end, "P").when(q == 1, "B1").otherwise("B2")
        wave = F.when(end, k + 1).when((q == 2) | (m == 2), k + 2).otherwise(k + 3)
    ftype = F.when(pos == 0, "I").when(q == 0, "P").when(closed, F.when(q == 2, "B2").otherwise("B1")).otherwise(kind)
    past_ref = F.when(pos == 0, none).when(q == 0, f - 4).when(closed, F.when(q == 2, f - 2).otherwise(f - 1)).otherwise(past)
    future_ref = F.when(q == 0, none).when(closed, F.when(q == 2, f + 2).otherwise(f + 1)).otherwise(future)
    wavefront = F.when(q == 0, k).when(closed, F.when(q == 2, b2).otherwise(b2 + 1)).otherwise(wave)
    order = F.when(pos == 0, 0).when(q == 0, 4 * (k - 1) + 1).when(closed, 4 * k + F.when(q == 2, 2).when(q == 1, 3).otherwise(4)).otherwise(4 * k + (F.when(q == m, 1).when(q == 2, 2).otherwise(3) if tail == "short_anchor" else q))
    return base.select("video_id", "frame_no", epoch.alias("epoch_no"), k.alias("segment_no"), ftype.alias("ftype"), past_ref.cast("int").alias("past_ref"), future_ref.cast("int").alias("future_ref"), wavefront.cast("int").alias("wavefront"), order.cast("int").alias("exec_order"), F.lit(False).alias("is_halo"), *payload)


def epoch_plan(frame_no: np.ndarray, last: np.ndarray, scheme: str = "reordered", reset_every: int = 20, tail: str = "chain", lookback: int = 1) -> tuple[np.ndarray, ...]:
    """(type number, wavefront, execution order, past, future, further past references ...) of frames, 0 for no reference: plan_frames' plan for rows which are in a task already.

    `last` is the greatest frame number of a frame's epoch, the next epoch's first frame included where it is there. It tells the tail, so no
    count by video has to be joined to the frames, and their tokens are shuffled once.
    """
    f = frame_no.astype(np.int64)
    pos = (f - 1) % reset_every
    none = np.zeros_like(f)
    if scheme == "sequential":
        refs = [np.where(pos >= k, f - k, 0) for k in range(1, lookback + 1)]
        return (np.where(pos == 0, 0, 1), pos, pos, refs[0], none, *refs[1:])
    q, k = pos % 4, pos // 4
    closed = f - q + 4 <= last
    b2 = 1 + np.maximum(k, np.where(pos - q + 4 == reset_every, 0, k + 1))
    m = last - (f - q)  # frames after the anchor in an open segment
    past, future, kind, wave, order = none, none, none, none, 4 * k + q
    if tail == "chain":
        past, kind, wave = f - 1, none + 1, k + q
    elif tail == "short_anchor":
        end = q == m
        past = np.where(end, f - q, np.where(q == 1, f - 1, f - 2))
        future = np.where(end, 0, f + 1)
        kind = np.where(end, 1, np.where(q == 1, 3, 2))
        wave = np.where(end, k + 1, np.where((q == 2) | (m == 2), k + 2, k + 3))
        order = 4 * k + np.where(end, 1, np.where(q == 2, 2, 3))
    pick = lambda start, anchor, two, one, open_: np.where(pos == 0, start, np.where(q == 0, anchor, np.where(closed, np.where(q == 2, two, one), open_)))
    return (
        pick(0, 1, 2, 3, kind),
        pick(0, k, b2, b2 + 1, wave),
        pick(0, 4 * (k - 1) + 1, 4 * k + 2, 4 * k + np.where(q == 1, 3, 4), order),
        pick(0, f - 4, f - 2, f - 1, past),
        pick(0, 0, f + 2, f + 1, future),
    )


def add_halo(plan: DataFrame) -> DataFrame:
    """Each epoch's first frame again at the end of the epoch before, whose last segment refers to it. It has no references, so its copy is equal."""
    starts = plan.where("ftype = 'I' and epoch_no > 0 and segment_no = 0")
    halo = starts.withColumns({"epoch_no": F.col("epoch_no") - 1, "is_halo": F.lit(True), "wavefront": F.lit(0), "exec_order": F.lit(0)})
    return plan.unionByName(halo)


def training_groups(plan: DataFrame, segments: int = 3, scheme: str = "reordered") -> DataFrame:
    """video_id, group_id, step, frame_no, ftype, past_ref, future_ref: anchors of `segments` segments and of the last one a B2 and a B1 frame.

    With scheme "sequential" a group is segments + 3 frames in a row; segments = 0 is each frame with its reference alone.
    """
    starts = plan.where("ftype = 'I' and not is_halo").select("video_id", F.col("frame_no").alias("s"))
    n = plan.groupBy("video_id").agg(F.max("frame_no").alias("n"))
    s = F.col("s")
    item = lambda no, kind, past, future: F.struct((s + no).alias("frame_no"), F.lit(kind).alias("ftype"), (s + past if past is not None else F.lit(None)).cast("int").alias("past_ref"), (s + future if future is not None else F.lit(None)).cast("int").alias("future_ref"))
    if scheme == "sequential" or not segments:
        size = segments + 3 if segments else 2
        items = [item(i, "I" if not i else "P", i - 1 if i else None, None) for i in range(size)]
        most = size - 1
    else:
        g = 4 * segments
        items = [item(4 * i, "P" if i else "I", 4 * i - 4 if i else None, None) for i in range(segments + 1)]
        items += [item(g - 2, "B2", g - 4, g), item(g - 1, "B1", g - 2, g)]
        most = g
    x = starts.join(n, "video_id").where(s + most <= F.col("n"))
    return x.select("video_id", F.col("s").alias("group_id"), F.posexplode(F.array(*items)).alias("step", "x")).select("video_id", "group_id", "step", "x.*")
