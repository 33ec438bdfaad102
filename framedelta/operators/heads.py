"""Linear heads over embeddings, frozen once fitted: what stands for the query models, which the encoder's savings must not disturb."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import vector as V


def fit(rows: DataFrame, sample: int = 4000, l2: float = 1e-3) -> tuple[np.ndarray, np.ndarray]:
    """(weights (dim + 1, targets), mean and deviation of the targets (2, targets)) by least squares on about `sample` rows of (video_id, frame_no, emb, y)."""
    n = max(1, rows.count())
    chance = F.pmod(F.xxhash64(F.lit("head"), F.col("video_id"), F.col("frame_no")), F.lit(1 << 30)) / float(1 << 30)
    got = rows.where(chance < min(1.0, sample / n)).select("video_id", "frame_no", "emb", "y").collect()
    got.sort(key=lambda r: (r["video_id"], r["frame_no"]))
    if not got:
        raise ValueError("no row to fit a head to")
    x, y = np.array([[*r["emb"], 1.0] for r in got]), np.array([r["y"] for r in got], float)
    w = np.linalg.solve(x.T @ x / len(x) + l2 * np.eye(x.shape[1]), x.T @ y / len(x))
    return w, np.stack([y.mean(0), y.std(0) + 1e-9])


def read(emb: Column, w: np.ndarray) -> Column:
    """What the heads see in an embedding."""
    return V.linear(emb, w[:-1], w[-1])


def standard(y: Column, scale: np.ndarray) -> Column:
    """Targets less their mean, over their deviation."""
    pairs = F.array(*[F.struct(F.lit(float(m)).alias("m"), F.lit(float(s)).alias("s")) for m, s in scale.T])
    return F.zip_with(y, pairs, lambda v, p: (v - p["m"]) / p["s"])


def strongest(y: Column) -> Column:
    """The place of the greatest number, the first of equals."""
    return (F.array_position(y, F.array_max(y)) - 1).cast("int")
