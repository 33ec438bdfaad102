"""Rewrites of an encode request before its plan is made, where Catalyst cannot see through the kernel."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import EncoderSpec, ReuseConfig


def closure(frames: DataFrame, cfg: ReuseConfig, videos: Column | None = None, lo: int | None = None, hi: int | None = None) -> DataFrame:
    """The frames that a request for frames lo..hi of some videos has to encode: whole epochs and the next one's first frame.

    Conditions on videos go down to the scan unchanged. One on frames would cut reference chains and so change values.
    The segment that closes the last epoch must not look like a video's tail, so one more frame comes with it.
    """
    x = frames if videos is None else frames.where(videos)
    r = cfg.reset_every
    if lo is not None:
        x = x.where(F.col("frame_no") > (lo - 1) // r * r)
    if hi is not None:
        x = x.where(F.col("frame_no") <= ((hi - 1) // r + 1) * r + 1)
    return x


def request(frames: DataFrame, spec: EncoderSpec, cfg: ReuseConfig, modules=None, videos: Column | None = None, lo: int | None = None, hi: int | None = None, pooled: bool = False) -> DataFrame:
    """EMBEDDINGS of the asked frames, equal to the same rows of a full encode; pooled: one mean vector for each video."""
    from ..functions import vector as V
    from ..operators.encode import gated_encode

    out = gated_encode(closure(frames.select("video_id", "frame_no", "tokens"), cfg, videos, lo, hi), spec, cfg, modules)
    if lo is not None:
        out = out.where(F.col("frame_no") >= lo)
    if hi is not None:
        out = out.where(F.col("frame_no") <= hi)
    return V.mean_pool(out, ["video_id"]) if pooled else out
