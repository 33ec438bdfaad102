"""Times of the headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]: one JSON line.

The encoders run on all activity frames. The ladder's rungs are one gate at 61 % reuse under more and more of the scheduling; all encoders,
the unmodified one included, have the same number of tasks and cores.
"""

import json
import os
import time

os.environ.setdefault("OMP_NUM_THREADS", "1")
os.environ.setdefault("OPENBLAS_NUM_THREADS", "1")

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from framedelta import experiments, workloads
from framedelta.model import EncoderSpec, ReuseConfig
from framedelta.operators import encode, training
from framedelta.pretrained import modules
from framedelta.sources import frames as S

#: Wide enough for the multiplies to weigh more than what is around them; raw tokens are projected by the embedding.
SPEC = EncoderSpec.preset("bench")
RHO = 0.61


def main() -> None:
    from dataclasses import replace

    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.shuffle.partitions", cpus).config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "8g").config("spark.executorEnv.OMP_NUM_THREADS", "1").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    took: dict[str, float] = {}

    def timed(name, make):
        t = time.time()
        make().write.format("noop").mode("overwrite").save()
        took[name] = round(time.time() - t, 3)

    frames = S.activity(spark, sf).repartition(int(cpus) * 3, "video_id").persist()
    n = frames.count()
    encode.full_encode(frames.limit(50), SPEC).count()
    weights = modules("bench")
    epochs = training.sample_epochs(frames, SPEC)
    learned = training.at_reuse(epochs, SPEC, ReuseConfig(), weights, RHO)
    mse = training.at_reuse(epochs, SPEC, ReuseConfig("sequential", gate="mse", calibrator=False), None, RHO)
    ways = {
        "full_encode": None,
        "gate_only": replace(learned, compaction="none", free_cache=False, batch_epochs=1),
        "plus_compaction": replace(learned, free_cache=False, batch_epochs=1),
        "plus_freed_caches_and_batches": learned,
        "learned_gate_trained_point": ReuseConfig(),
        "learned_gate_high_reuse": training.at_reuse(epochs, SPEC, ReuseConfig(), weights, 0.85),
        "mse_gate": mse,
        "budget_gate": ReuseConfig("sequential", gate="budget", budget=2, calibrator=False),
        "prune_merge": (1, 1),
    }
    for name, way in ways.items():
        timed(name, lambda w=way: experiments.encoded(frames, SPEC, w, weights))
    reuse = {name: round(experiments.encoded(frames, SPEC, ways[name], weights).agg(F.avg("reuse_rate")).first()[0], 3) for name in ("plus_freed_caches_and_batches", "learned_gate_trained_point", "mse_gate")}
    frames.unpersist()
    for name in ("plan_reordered", "mse_gate_map", "budget_gate_map", "retrieval_top5", "multiple_choice", "grounding_spans"):
        timed(name, lambda q=name: workloads.QUERIES[q](spark, sf))
    speed = {k: round(took["full_encode"] / took[k], 3) for k in ways}
    print(json.dumps({"metric": "total_seconds", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": sf, "frames": n, "frames_per_second_full": round(n / took["full_encode"], 1), "throughput_x": speed, "reuse_rate": reuse}))


if __name__ == "__main__":
    main()
