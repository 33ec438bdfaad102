"""Encoding of live frames: a queue of one segment per video, or none where frames must not wait.

State per video is the raw tokens of the epoch so far, at most reset_every frames, and the number of the next frame. Cached
activations are not kept in the state, where they would weigh far more than the frames: a closing segment rebuilds them from its epoch.
So results are those of the batch plan, and a lost executor costs no more than its state's last checkpoint.
"""

from __future__ import annotations

import io
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import EncoderSpec, ReuseConfig
from ..operators import kernel
from ..operators.encode import ship

OUT = "video_id bigint, frame_no int, emb array<double>, reuse_rate double"
STATE = "next int, data binary"


def local_plan(pos: np.ndarray, cfg: ReuseConfig, closed: bool) -> tuple[np.ndarray, ...]:
    """(past, future, type, wavefront) of frames at positions 0, 1, ... of one epoch, as row numbers; `closed` if the last of them is an anchor.

    Position reset_every is the next epoch's first frame. An open last segment follows the tail rule "chain".
    """
    past, future, kind, wave = ([] for _ in range(4))
    n = len(pos)
    for p in range(n):
        q, k = p % 4, p // 4
        if p == 0 or p == cfg.reset_every:
            row = (-1, -1, 0, 0)
        elif cfg.scheme == "sequential":
            row = (p - 1, -1, 1, p)
        elif q == 0:
            row = (p - 4, -1, 1, k)
        elif p - q + 4 < n:
            b2 = 1 + max(k, 0 if p - q + 4 == cfg.reset_every else k + 1)
            row = (p - 2, p + 2, 2, b2) if q == 2 else (p - 1, p + 1, 3, b2 + 1)
        else:
            row = (p - 1, -1, 1, k + q)
        for x, v in zip((past, future, kind, wave), row, strict=True):
            x.append(v)
    return tuple(map(np.array, (past, future, kind, wave)))


def stream_encode(frames: DataFrame, spec: EncoderSpec, cfg: ReuseConfig, modules: list[dict] | None = None, idle: str | None = None, max_ahead: int = 40) -> DataFrame:
    """A stream of OUT rows from a stream of video_id, frame_no, tokens, each frame once.

    Scheme "reordered" emits a segment when its closing anchor is there; "sequential" emits each frame at once. Frames before the next one
    expected (repeats and late ones) are dropped. A gap is waited for until `max_ahead` later frames are there; then the frame before it stands in for
    the missing ones, which are never emitted, so the state is bounded. With idle (a duration), a silent video's open segment is emitted by the tail rule.
    """
    ship(frames.sparkSession)
    sent = frames.sparkSession.sparkContext.broadcast(modules)
    shape = (spec.n_tokens, spec.in_dim)
    wait_ms = int(pd.Timedelta(idle).total_seconds() * 1000) if idle else None

    def emit(video, first, raw, done, upto, missing):
        """Rows of the epoch's frames done .. upto - 1 that are not missing; `first` is the epoch's first frame number."""
        past, future, kind, wave = local_plan(np.arange(len(raw)), cfg, True)
        out = kernel.gated(raw, past, future, kind, wave, spec, cfg, sent.value)
        rate = out.reuse[:, :, 1:].mean((1, 2))
        return [(video, first + i, out.emb[i].tolist(), float(rate[i])) for i in range(done, upto) if first + i not in missing]

    def step(key, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        video = int(key[0])
        expect, raw, seen = 1, np.zeros((0, *shape)), {}
        done = 0  # frames of the epoch that are out
        missing: set[int] = set()  # numbers in the epoch for which another frame stands in
        if state.exists:
            expect, data = state.get
            with np.load(io.BytesIO(data)) as z:
                raw, done = z["raw"], int(z["done"])
                seen = dict(zip(z["early_no"].tolist(), z["early"], strict=True))
                missing = set(z["missing"].tolist())
        rows = []
        if state.hasTimedOut:
            rows += emit(video, expect - len(raw), raw, done, len(raw), missing)
            done = len(raw)
        for p in parts:
            for no, tok in zip(p["frame_no"], p["tokens"], strict=True):
                if no >= expect:
                    seen.setdefault(int(no), np.reshape(tok, shape))
        while expect in seen or len(seen) >= max_ahead:
            if expect not in seen:
                missing.add(expect)
                seen[expect] = raw[-1] if len(raw) else np.zeros(shape)
            missing = {m for m in missing if m > expect - cfg.reset_every - 2}
            raw = np.concatenate([raw, seen.pop(expect)[None]])
            expect += 1
            first, n = expect - len(raw), len(raw)
            if cfg.scheme == "sequential":
                if n <= cfg.reset_every:
                    rows += emit(video, first, raw, done, n, missing)
                    done = n
                else:
                    raw, done = raw[-1:], 0
                    rows += emit(video, expect - 1, raw, 0, 1, missing)
                    done = 1
            elif (n - 1) % 4 == 0:
                ready = min(n, cfg.reset_every)
                rows += emit(video, first, raw, done, ready, missing)
                done = ready
                if n > cfg.reset_every:  # the next epoch begins with this frame
                    raw = raw[-1:]
                    rows += emit(video, expect - 1, raw, 0, 1, missing)
                    done = 1
        buf = io.BytesIO()
        early = sorted(seen)
        np.savez(buf, raw=raw, done=done, missing=np.array(sorted(missing), np.int64), early_no=np.array(early, np.int64), early=np.array([seen[i] for i in early]).reshape(-1, *shape))
        state.update((expect, buf.getvalue()))
        if wait_ms and done < len(raw):
            state.setTimeoutDuration(wait_ms)
        yield pd.DataFrame(rows, columns=["video_id", "frame_no", "emb", "reuse_rate"])

    timeout = "ProcessingTimeTimeout" if idle else "NoTimeout"
    return frames.where(F.col("video_id").isNotNull()).groupBy("video_id").applyInPandasWithState(step, OUT, STATE, "append", timeout)


def event_ticks(events: DataFrame, tick: str = "6 hours", late: str = "6 hours") -> DataFrame:
    """Totals by user, type and tick from a stream of events: repeats of an event_id within the watermark count once, later ones are dropped."""
    e = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
    return e.groupBy("user_id", "event_type", F.window("ts", tick).alias("w")).agg(F.sum("value").alias("total"), F.count(F.lit(1)).alias("n"))


def sliding_totals(events: DataFrame, length: str = "72 hours", step: str = "6 hours", late: str = "6 hours") -> DataFrame:
    """Totals by user in overlapping windows, from a stream or a table of events."""
    e = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    return e.groupBy("user_id", F.window("ts", length, step).alias("w")).agg(F.sum("value").alias("total"), F.count(F.lit(1)).alias("n"))


def scored(embeddings: DataFrame, queries: DataFrame, least: float = -1.0) -> DataFrame:
    """A stream of embeddings against a static, broadcast set of queries (query_id, vec): query_id, video_id, frame_no, score of at least `least`."""
    from ..functions import vector as V

    x = embeddings.join(F.broadcast(queries.select("query_id", "vec")))
    return x.select("query_id", "video_id", "frame_no", V.cosine(F.col("vec"), F.col("emb")).alias("score")).where(F.col("score") >= least)


def annotated(events: DataFrame, notes: DataFrame, within: str = "6 hours", late: str = "6 hours") -> DataFrame:
    """Two streams joined: events (user_id, ts, ...) with notes (user_id, note_ts, note) made up to `within` after them. Both have watermarks, so state is dropped."""
    e = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    n = notes.select(F.col("user_id").alias("_u"), F.col("note_ts").cast("timestamp").alias("note_ts"), "note").withWatermark("note_ts", late)
    near = (F.col("user_id") == F.col("_u")) & (F.col("note_ts") >= F.col("ts")) & (F.col("note_ts") <= F.col("ts") + F.expr(f"INTERVAL {within}"))
    return e.join(n, near).drop("_u")


def queue_latency(fps: float = 2.0, segment: int = 4) -> float:
    """Seconds for which the first frame of a segment waits for its closing anchor."""
    return segment / fps
