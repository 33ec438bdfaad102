"""python -m framedelta.train SF_DIR: fits the gates and calibrators that are shipped in weights.json, on training videos alone.

Every set is fitted by the same number of steps to a bounded sample of groups; the names say what is left out or changed.
"""

from __future__ import annotations

import multiprocessing
import sys
import time
from pathlib import Path

from pyspark.sql import SparkSession

from .model import EncoderSpec
from .operators import training
from .pretrained import as_json, modules, names
from .sources import frames as S

TINY = EncoderSpec.preset("tiny")
PROSE = EncoderSpec.preset("tiny", n_tokens=9, in_dim=16)
SHIP = EncoderSpec.preset("tiny", n_tokens=7, in_dim=7)
MORPH = EncoderSpec.preset("tiny", n_tokens=9, in_dim=8)
BENCH = EncoderSpec.preset("bench")
TARGETS = (0.3, 0.5, 0.7, 0.9)

#: name: (frames, encoder, options of the fit)
SETS: dict[str, tuple] = {
    "activity": (S.activity, TINY, {}),
    "morph": (S.morph, MORPH, {}),
    "prose": (S.prose, PROSE, {}),
    "talk": (S.talk, PROSE, {"segments": 1, "r_target": 0.4}),
    "ship": (S.shipping, SHIP, {"r_target": 0.5}),
    "bench": (S.activity, BENCH, {"steps": 80, "batch": 32}),
    **{f"activity g{g}": (S.activity, TINY, {"segments": g}) for g in (1, 2, 4)},
    "activity sequential": (S.activity, TINY, {"scheme": "sequential"}),
    "activity frame-wise": (S.activity, TINY, {"segments": 0}),
    **{f"activity target {r}": (S.activity, TINY, {"r_target": r}) for r in TARGETS},
    "activity gate": (S.activity, TINY, {"segments": 0, "scheme": "sequential", "calibrator": False}),
    "activity gate, order": (S.activity, TINY, {"segments": 0, "calibrator": False}),
    "activity gate, order, grouping": (S.activity, TINY, {"calibrator": False}),
}


def _fit(job) -> tuple:
    name, spec, groups, options = job
    t = time.time()
    found, log = training.fit_reuse(groups, spec, **{"r_target": 0.6, "steps": 150, **options})
    print(name, len(groups), [round(x, 4) for x in log[-1][1:4]], f"{time.time() - t:.0f} s", flush=True)
    return name, found


def main(sf: str, only: list[str]) -> None:
    spark = SparkSession.builder.master("local[*]").config("spark.sql.shuffle.partitions", "16").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "8g").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    path = Path(__file__).with_name("weights.json")
    jobs, made = [], {}
    for name, (maker, spec, options) in SETS.items():
        if not only or name in only:
            if maker not in made:
                made[maker] = maker(spark, sf).persist()
            groups = training.sample_groups(made[maker], spec, options.get("segments", 3), 600, scheme=options.get("scheme", "reordered"))
            jobs.append((name, spec, groups, options))
    spark.stop()
    done = {n: modules(n) for n in names() if n in SETS}
    with multiprocessing.get_context("spawn").Pool(8) as pool:
        done |= dict(pool.imap_unordered(_fit, sorted(jobs, key=lambda j: j[0] != "bench")))
    path.write_text(as_json({n: done[n] for n in sorted(done)}))


if __name__ == "__main__":
    main(sys.argv[1], sys.argv[2:])
