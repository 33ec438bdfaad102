"""Table functions and an aggregate for SQL text: fd_plan, fd_group, fd_cache_steps, fd_vector_mean."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F


def register(spark: SparkSession) -> None:
    from ..operators.encode import ship

    ship(spark)

    @F.udtf(returnType="frame_no int, ftype string, past_ref int, future_ref int, wavefront int, exec_order int")
    class Plan:
        """The plan of a video of n frames."""

        def eval(self, n: int, scheme: str, reset_every: int):
            from framedelta.model import TYPES
            from framedelta.plans.reference import epoch_plan

            f = np.arange(1, n + 1)
            last = np.minimum(n, ((f - 1) // reset_every + 1) * reset_every + 1)
            kind, wave, order, past, future = epoch_plan(f, last, scheme, reset_every)
            for row in zip(f, kind, past, future, wave, order, strict=True):
                no, k, p, u, w, o = map(int, row)
                yield no, TYPES[k], p or None, u or None, w, o

    @F.udtf(returnType="step int, frame_no int, ftype string, past_ref int, future_ref int")
    class Group:
        """A training group of some segments that begins at a frame."""

        def eval(self, start: int, segments: int, scheme: str):
            from framedelta.model import TYPES
            from framedelta.operators.training import group_refs

            offsets, refs, kinds = group_refs(segments, scheme)
            for i, ((past, future), k) in enumerate(zip(refs, kinds, strict=True)):
                at = lambda r: None if r < 0 else start + offsets[r]
                yield i, start + offsets[i], TYPES[int(k)], at(past), at(future)

    @F.udtf(returnType="step int, layer int, segment int, live int")
    class CacheSteps:
        """Live cached frames after each layer of some segments of four frames, layer by layer with freeing: the old anchors' caches, and the segment at work."""

        def eval(self, layers: int, segments: int):
            live, step = 0, 0
            for s in range(segments):
                for layer in range(layers):
                    live += 4
                    yield step, layer, s, live
                    live -= 3 + (s > 0)
                    step += 1

    spark.udtf.register("fd_plan", Plan)
    spark.udtf.register("fd_group", Group)
    spark.udtf.register("fd_cache_steps", CacheSteps)

    @F.pandas_udf("array<double>")
    def vector_mean(v: pd.Series) -> list:
        return np.stack(v.to_list()).astype(float).mean(0).tolist()

    spark.udf.register("fd_vector_mean", vector_mean)
