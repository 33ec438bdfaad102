"""Encoding as a plan: one shuffle that brings an epoch's frames together, one Arrow crossing, no driver loop."""

from __future__ import annotations

import copy

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import EMBEDDINGS, EncoderSpec, ReuseConfig
from ..plans.reference import SCHEMES, TAILS, epoch_plan
from . import kernel

KEYS = ("video_id", "epoch_no", "frame_no")
FLAT_ROWS = 512  # frames of a batch where each frame stands alone


def ship(spark) -> None:
    """Send this package (its numpy and plan parts) to the executors once per application."""
    import io
    import tempfile
    import uuid
    import zipfile
    from pathlib import Path

    sc = spark.sparkContext
    if getattr(sc, "_framedelta_core", False):
        return
    root = Path(__file__).resolve().parents[1]
    buf = io.BytesIO()
    with zipfile.ZipFile(buf, "w") as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, str(p.relative_to(root.parent)))
    path = Path(tempfile.mkdtemp(prefix="framedelta-code-")) / f"framedelta_core_{uuid.uuid4().hex[:8]}.zip"
    path.write_bytes(buf.getvalue())
    sc.addPyFile(str(path))
    sc._framedelta_core = True


def fixed(b: pa.RecordBatch | pa.Table, column: str, want: int, of: str, what: str) -> np.ndarray:
    """(rows, want) of an array column; ragged or null arrays and NaN are errors, which name the row's `of`."""
    col = b.column(column)
    col = col.combine_chunks() if isinstance(col, pa.ChunkedArray) else col
    bad = col.value_lengths().fill_null(-1).to_numpy(zero_copy_only=False) != want
    if not bad.any():
        x = col.flatten().to_numpy(zero_copy_only=False).astype(np.float64, copy=False).reshape(-1, want)  # a null becomes NaN
        bad = np.isnan(x).any(1)
    if bad.any():
        raise ValueError(f"a {what} needs {want} numbers: {of} {b.column(of)[int(bad.argmax())].as_py()}")
    return x


def tokens_of(b: pa.RecordBatch | pa.Table, spec: EncoderSpec) -> np.ndarray:
    """(frames, tokens, values) of a batch."""
    return fixed(b, "tokens", spec.n_tokens * spec.in_dim, "video_id", "frame").reshape(-1, spec.n_tokens, spec.in_dim)


def _lists(x: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(np.arange(0, x.size + 1, x.shape[1], dtype=np.int32), pa.array(x.ravel()))


def full_encode(frames: DataFrame, spec: EncoderSpec) -> DataFrame:
    """EMBEDDINGS by the unmodified encoder: no references, so no plan and no shuffle."""
    ship(frames.sparkSession)

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, FLAT_ROWS):
                x = b.slice(at, FLAT_ROWS)
                z = kernel.exact(tokens_of(x, spec), spec)
                n = len(z)
                yield pa.RecordBatch.from_arrays([x.column("video_id"), x.column("frame_no"), _lists(z), pa.array(np.zeros(n)), pa.array(np.full(n, float(kernel.flops_exact(spec))))], ["video_id", "frame_no", "emb", "reuse_rate", "flops"])

    return frames.select("video_id", "frame_no", "tokens").mapInArrow(run, EMBEDDINGS)


def intra_frame_reduce(frames: DataFrame, spec: EncoderSpec, prune: int | tuple[int, ...] = 1, merge: int | tuple[int, ...] = 1) -> DataFrame:
    """EMBEDDINGS of the in-frame baseline: prune by class attention, merge by likeness. It reuses nothing, so its reuse_rate is null."""
    ship(frames.sparkSession)

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, FLAT_ROWS):
                x = b.slice(at, FLAT_ROWS)
                z, flops = kernel.reduced(tokens_of(x, spec), spec, prune, merge)
                yield pa.RecordBatch.from_arrays([x.column("video_id"), x.column("frame_no"), _lists(z), pa.nulls(len(z), pa.float64()), pa.array(np.full(len(z), flops))], ["video_id", "frame_no", "emb", "reuse_rate", "flops"])

    return frames.select("video_id", "frame_no", "tokens").mapInArrow(run, EMBEDDINGS)


def encode_partitions(frames: DataFrame) -> int:
    """How many tasks encode: all of shuffle.partitions, and three for each core. Given as a number, so that adaptive execution does not merge
    them: it goes by bytes, and a frame costs far more than its bytes say."""
    spark = frames.sparkSession
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), 3 * spark.sparkContext.defaultParallelism)


def partitions_for(frames: DataFrame, spec: EncoderSpec, task_flops: float = 2e12, task_bytes: int = 256 << 20) -> int:
    """Tasks for a corpus of known size: by the exact encoder's work and by the tokens' bytes, no fewer than encode_partitions. Counts the frames."""
    n = frames.select("video_id").count()
    return max(encode_partitions(frames), int(n * kernel.flops_exact(spec) / task_flops) + 1, n * spec.n_tokens * spec.in_dim * 8 // task_bytes + 1)


def check(cfg: ReuseConfig) -> None:
    if cfg.scheme not in SCHEMES or cfg.tail not in TAILS:
        raise ValueError("unknown scheme or tail rule")
    if cfg.scheme == "reordered" and cfg.reset_every % 4:
        raise ValueError("reset_every must be a multiple of 4")


def colocated(frames: DataFrame, cfg: ReuseConfig, partitions: int | None = None) -> DataFrame:
    """Frames with their epoch and, in the reordered scheme, the copy of the next epoch's first one; an epoch together and in order.

    One shuffle of the tokens, by (video, epoch), so that a long video is many small units. The plan itself is made in the tasks.
    """
    check(cfg)
    e = F.floor((F.col("frame_no") - 1) / cfg.reset_every).cast("int")
    x = frames.select("video_id", "frame_no", e.alias("_own"), "tokens")
    if cfg.scheme == "reordered":
        first = (F.col("_own") > 0) & (F.pmod(F.col("frame_no") - 1, F.lit(cfg.reset_every)) == 0)
        x = x.withColumn("epoch_no", F.explode(F.when(first, F.array(F.col("_own"), F.col("_own") - 1)).otherwise(F.array("_own"))))
    else:
        x = x.withColumn("epoch_no", F.col("_own"))
    x = x.select(*KEYS, (F.col("epoch_no") < F.col("_own")).alias("is_halo"), "tokens")
    return x.repartition(partitions or encode_partitions(frames), "video_id", "epoch_no").sortWithinPartitions(*KEYS)


def whole_epochs(batches, at_once: int):
    """Tables of at most `at_once` whole epochs: what an Arrow batch leaves of its last epoch goes to the next one."""
    held: pa.Table | None = None
    for b in batches:
        t = pa.Table.from_batches([b])
        t = pa.concat_tables([held, t]).combine_chunks() if held is not None else t
        if not t.num_rows:
            continue
        video, epoch = (t.column(c).to_numpy(zero_copy_only=False) for c in KEYS[:2])
        cuts = np.flatnonzero((np.diff(video) != 0) | (np.diff(epoch) != 0)) + 1
        at = 0
        for end in cuts[at_once - 1 :: at_once]:
            yield t.slice(at, end - at)
            at = int(end)
        held = t.slice(at)
    if held is not None and held.num_rows:
        video, epoch = (held.column(c).to_numpy(zero_copy_only=False) for c in KEYS[:2])
        cuts = [0, *(np.flatnonzero((np.diff(video) != 0) | (np.diff(epoch) != 0)) + 1)[at_once - 1 :: at_once].tolist(), held.num_rows]
        for a, e in zip(cuts, cuts[1:], strict=False):
            if e > a:
                yield held.slice(a, e - a)


class Epochs:
    """Whole epochs in a task, and what the ways that encode them share: the first layer's attention and what gates see of the same references."""

    def __init__(self, t: pa.Table, spec: EncoderSpec):
        get = lambda c: t.column(c).to_numpy(zero_copy_only=False)
        self.spec, self.video, self.no, self.halo = spec, get("video_id"), get("frame_no"), get("is_halo").astype(bool)
        self.change = np.append(True, (np.diff(self.video) != 0) | (np.diff(get("epoch_no")) != 0))
        self.raw = tokens_of(t, spec)
        self.begun = kernel.start(self.raw, spec)
        self.plans: dict = {}

    def plan(self, cfg: ReuseConfig):
        key = (cfg.scheme, cfg.reset_every, cfg.tail, cfg.lookback)
        if key not in self.plans:
            part = np.cumsum(self.change) - 1
            last = self.no[np.append(np.flatnonzero(self.change)[1:], len(self.no)) - 1][part]
            kind, wave, exec_order, *refs = epoch_plan(self.no, last, cfg.scheme, cfg.reset_every, cfg.tail, cfg.lookback)
            kind, wave, exec_order = (np.where(self.halo, 0, v) for v in (kind, wave, exec_order))  # a copy has no references
            refs = kernel.rows_of(self.no, part, *(np.where(self.halo, 0, r) for r in refs))
            self.plans[key] = kind, wave, np.lexsort((exec_order, part)), refs, sum((r >= 0).astype(int) for r in refs), []
        return self.plans[key]

    def gated(self, cfg: ReuseConfig, modules: list[dict] | None):
        """(what the kernel did, reuse rate and FLOPs of each frame)."""
        kind, wave, order, (past, future, *more), n_refs, hints = self.plan(cfg)
        done = kernel.gated(self.raw, past, future, kind, wave, self.spec, cfg, modules, order, more=tuple(more), begun=self.begun, hints=hints)
        flops = kernel.flops_gated(self.spec, done.reuse.sum(2), cfg.gate, cfg.calibrator and modules is not None, n_refs, inputs=len(modules[0]["g1"]) if modules is not None else kernel.INPUTS)
        return done, done.reuse[:, :, 1:].mean((1, 2)), flops


def against_exact(frames: DataFrame, spec: EncoderSpec, ways: list, partitions: int | None = None) -> DataFrame:
    """way (its place in the list), video_id, cosine, reuse_rate, flops, full: every frame by every way against the exact embedding, and the FLOPs of both.

    A way is (ReuseConfig, modules), (prune, merge), or None for the unmodified encoder. All ways of a reset period encode an epoch where it lies, so the tokens move once and no embedding moves.
    """
    from .search import cosines, lengths

    spark = frames.sparkSession
    ship(spark)
    plain = [not hasattr(w[0], "gate") if w else True for w in ways]
    resets = sorted({w[0].reset_every for w, p in zip(ways, plain, strict=True) if not p}) or [ReuseConfig().reset_every]
    out = None
    for reset in resets:
        mine = {}
        for k, (w, p) in enumerate(zip(ways, plain, strict=True)):
            if (reset == resets[0]) if p else w[0].reset_every == reset:
                if not p and w[1] is None and (w[0].gate == "learned" or w[0].calibrator) and w[0].gate != "never":
                    w = (w[0], kernel.new_modules(spec, own_type=w[0].own_type))
                mine[k] = w
        cfgs = [w[0] for k, w in mine.items() if not plain[k]] or [ReuseConfig()]
        halo = [c for c in cfgs if c.scheme == "reordered" and c.gate != "never" and reset > 1]
        for c in cfgs:
            check(c)
        rows = colocated(frames, (halo or cfgs)[0], partitions)
        at_once = min(c.epochs_at_once(spec) for c in cfgs)
        sent = spark.sparkContext.broadcast((mine, plain, bool(halo)))

        def run(batches):
            mine, plain, halo = sent.value  # noqa: B023
            full = float(kernel.flops_exact(spec))
            for t in whole_epochs(batches, at_once):  # noqa: B023
                x = Epochs(t, spec)
                keep = np.flatnonzero(~x.halo)
                own = x
                if halo:  # the next epoch's first frame is there for the reordered scheme alone
                    own = copy.copy(x)
                    own.video, own.no, own.halo, own.raw, own.begun, own.plans = x.video[keep], x.no[keep], x.halo[keep], x.raw[keep], (x.begun[0][keep], x.begun[1][keep]), {}
                    own.change = x.change[keep]
                z = kernel.exact(own.raw, spec, own.begun)
                n, nz = len(z), lengths(z)
                cols: list[list] = [[] for _ in range(4)]
                for k, w in mine.items():
                    rate, flops = np.zeros(n), np.full(n, full)
                    if w is None or (not plain[k] and (w[0].gate == "never" or w[0].reset_every == 1)):
                        emb = z
                    elif plain[k]:
                        emb, cost = kernel.reduced(own.raw, spec, *w, begun=own.begun)
                        rate, flops = None, np.full(n, cost)
                    else:
                        at = x if w[0].scheme == "reordered" else own
                        done, rate, flops = at.gated(*w)
                        emb = done.emb
                        if at is not own:
                            emb, rate, flops = emb[keep], rate[keep], flops[keep]
                    for c, v in zip(cols, (pa.array(np.full(n, k, np.int32)), pa.array(cosines(emb, z, lengths(emb), nz)), pa.nulls(n, pa.float64()) if rate is None else pa.array(rate), pa.array(flops)), strict=True):
                        c.append(v)
                way, cosine, rate, flops = map(pa.concat_arrays, cols)
                yield pa.RecordBatch.from_arrays([way, pa.array(np.tile(own.video, len(mine))), cosine, rate, flops, pa.array(np.full(len(way), full))], AGAINST_NAMES)

        part = rows.mapInArrow(run, AGAINST)
        out = part if out is None else out.unionAll(part)
    return out


def schedule_costs(frames: DataFrame, spec: EncoderSpec, cfgs: list[ReuseConfig], modules: list[dict], partitions: int | None = None) -> DataFrame:
    """way (its place in the list), multiplies, rows, peak, reuse (the sum of the frames' rates), frames: what each batch of epochs cost by every schedule.

    The schedules have the same references and batches, so a batch is encoded by all of them where it lies and the tokens move once.
    """
    spark = frames.sparkSession
    ship(spark)
    sent = spark.sparkContext.broadcast((cfgs, modules))
    rows = colocated(frames, cfgs[0], partitions)
    at_once = cfgs[0].epochs_at_once(spec)
    if any((c.scheme, c.reset_every, c.epochs_at_once(spec)) != (cfgs[0].scheme, cfgs[0].reset_every, at_once) for c in cfgs):
        raise ValueError("schedules are compared on the same batches")

    def run(batches):
        cfgs, modules = sent.value
        for t in whole_epochs(batches, at_once):
            x = Epochs(t, spec)
            done, rate, _ = zip(*(x.gated(c, modules) for c in cfgs), strict=True)
            counts = [pa.array([d.count[c] for d in done], pa.int64()) for c in ("multiplies", "rows", "peak")]
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(cfgs), dtype=np.int32)), *counts, pa.array([float(r[~x.halo].sum()) for r in rate]), pa.array([int((~x.halo).sum())] * len(cfgs), pa.int64())], COST_NAMES)

    return rows.mapInArrow(run, COSTS)


COSTS = "way int, multiplies bigint, rows bigint, peak bigint, reuse double, frames bigint"
COST_NAMES = [c.split(" ")[0] for c in COSTS.split(", ")]
AGAINST = "way int, video_id bigint, cosine double, reuse_rate double, flops double, full double"
AGAINST_NAMES = [c.split(" ")[0] for c in AGAINST.split(", ")]
OUT = EMBEDDINGS + ", map binary, reused array<bigint>, multiplies bigint, rows bigint, peak bigint"


def gated_encode(frames: DataFrame, spec: EncoderSpec, cfg: ReuseConfig, modules: list[dict] | None = None, partitions: int | None = None, with_costs: bool = False) -> DataFrame:
    """EMBEDDINGS by reuse under cfg. with_costs adds the reuse map (bits of layers x tokens) and, on one frame of each batch, its counts.

    Without any references (reset_every 1) or with gate "never" this is full_encode, and nothing is shuffled.
    """
    if not with_costs and (cfg.reset_every == 1 or cfg.gate == "never"):
        return full_encode(frames, spec)
    spark = frames.sparkSession
    ship(spark)
    modules = modules if modules is not None else (kernel.new_modules(spec, own_type=cfg.own_type) if cfg.gate == "learned" or cfg.calibrator else None)
    sent = spark.sparkContext.broadcast(modules)
    rows = colocated(frames, cfg, partitions)
    at_once = cfg.epochs_at_once(spec)

    def run(batches):
        for t in whole_epochs(batches, at_once):
            x = Epochs(t, spec)
            keep = np.flatnonzero(~x.halo)
            done, rate, flops = x.gated(cfg, sent.value)
            cols = [pa.array(x.video[keep]), pa.array(x.no[keep].astype(np.int32)), _lists(done.emb[keep]), pa.array(rate[keep]), pa.array(flops[keep])]
            names = ["video_id", "frame_no", "emb", "reuse_rate", "flops"]
            if with_costs:
                bits = np.packbits(done.reuse[keep].reshape(len(keep), -1), axis=1)
                once = lambda v: pa.array([v] + [None] * (len(keep) - 1), pa.int64())  # noqa: E731, B023
                cols += [pa.array([y.tobytes() for y in bits], pa.binary()), _lists(done.reuse[keep].sum(2).astype(np.int64)), once(done.count["multiplies"]), once(done.count["rows"]), once(done.count["peak"])]
                names += ["map", "reused", "multiplies", "rows", "peak"]
            yield pa.RecordBatch.from_arrays(cols, names)

    return rows.mapInArrow(run, OUT if with_costs else EMBEDDINGS)
