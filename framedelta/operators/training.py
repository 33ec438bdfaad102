"""Training of gates and calibrators by gradient descent through soft gates; the backbone stays frozen.

A small tape gives reverse-mode gradients of the operations that a group's forward pass needs. Groups run all their frames in reference
order, so an error made in one frame is felt in those that reuse it. Decisions are relaxed by Gumbel noise and a falling temperature.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import EncoderSpec
from . import kernel


class Var:
    """A value on the tape: parents with functions that bring the gradient back."""

    __slots__ = ("v", "g", "back")

    def __init__(self, v, back=()):
        self.v, self.g, self.back = np.asarray(v, float), None, back

    def __add__(self, o):
        return add(self, o)

    def __matmul__(self, o):
        return matmul(self, o)

    def __mul__(self, o):
        return mul(self, o)


def value(x) -> np.ndarray:
    return x.v if isinstance(x, Var) else np.asarray(x, float)


def _fit(g: np.ndarray, shape: tuple) -> np.ndarray:
    """g summed over what broadcasting added."""
    while g.ndim > len(shape):
        g = g.sum(0)
    for i, n in enumerate(shape):
        if n == 1 and g.shape[i] != 1:
            g = g.sum(i, keepdims=True)
    return g


def op(v, *pairs) -> Var:
    return Var(v, [(p, f) for p, f in pairs if isinstance(p, Var)])


def add(a, b):
    return op(value(a) + value(b), (a, lambda g: _fit(g, value(a).shape)), (b, lambda g: _fit(g, value(b).shape)))


def mul(a, b):
    return op(value(a) * value(b), (a, lambda g: _fit(g * value(b), value(a).shape)), (b, lambda g: _fit(g * value(a), value(b).shape)))


def matmul(a, b):
    x, y = value(a), value(b)

    def to_b(g):
        return x.reshape(-1, x.shape[-1]).T @ g.reshape(-1, g.shape[-1]) if y.ndim == 2 else np.swapaxes(x, -1, -2) @ g

    return op(x @ y, (a, lambda g: g @ np.swapaxes(y, -1, -2)), (b, to_b))


def unary(a, v, slope):
    return op(v, (a, lambda g: g * slope))


def relu(a):
    return unary(a, np.maximum(value(a), 0), value(a) > 0)


def sigmoid(a):
    s = 1 / (1 + np.exp(-np.clip(value(a), -40, 40)))
    return unary(a, s, s * (1 - s))


def gelu(a):
    x = value(a)
    t = np.tanh(0.7978845608028654 * (x + 0.044715 * (x * x * x)))
    return unary(a, 0.5 * x * (1 + t), 0.5 * (1 + t) + 0.5 * x * (1 - t * t) * 0.7978845608028654 * (1 + 3 * 0.044715 * x * x))


def norm(a):
    x = value(a)
    c = x - x.mean(-1, keepdims=True)
    s = np.sqrt((c * c).mean(-1, keepdims=True) + 1e-6)
    y = c / s

    def back(g):
        return (g - g.mean(-1, keepdims=True) - y * (g * y).mean(-1, keepdims=True)) / s

    return op(y, (a, back))


def softmax(a):
    e = np.exp(value(a) - value(a).max(-1, keepdims=True))
    p = e / e.sum(-1, keepdims=True)
    return op(p, (a, lambda g: p * (g - (g * p).sum(-1, keepdims=True))))


def reshape(a, shape):
    return op(value(a).reshape(shape), (a, lambda g: g.reshape(value(a).shape)))


def transpose(a, axes):
    return op(value(a).transpose(axes), (a, lambda g: g.transpose(np.argsort(axes))))


def take(a, key):
    def back(g):
        out = np.zeros_like(value(a))
        np.add.at(out, key, g)
        return out

    return op(value(a)[key], (a, back))


def concat(parts, axis=-1):
    sizes = np.cumsum([value(p).shape[axis] for p in parts])[:-1]
    return op(np.concatenate([value(p) for p in parts], axis), *[(p, lambda g, i=i: np.split(g, sizes, axis)[i]) for i, p in enumerate(parts)])


def mean(a):
    return op(value(a).mean(), (a, lambda g: np.full(value(a).shape, g / value(a).size)))


def cosine_to(a, z):
    """Cosines of rows of a to fixed rows z."""
    x = value(a)
    nx, nz = np.linalg.norm(x, axis=-1, keepdims=True) + 1e-12, np.linalg.norm(z, axis=-1, keepdims=True) + 1e-12
    c = (x * z).sum(-1, keepdims=True) / (nx * nz)
    return op(c[..., 0], (a, lambda g: g[..., None] * (z / (nx * nz) - c * x / nx**2)))


def backward(out: Var) -> None:
    order, seen = [], set()
    todo = [(out, False)]
    while todo:
        v, ready = todo.pop()
        if ready:
            order.append(v)
        elif id(v) not in seen:
            seen.add(id(v))
            todo.append((v, True))
            todo += [(p, False) for p, _ in v.back]
    out.g = np.ones_like(out.v)
    for v in reversed(order):
        for p, f in v.back:
            g = f(v.g)
            p.g = g if p.g is None else p.g + g


def gumbel(seed: int, step: int, shape: tuple) -> np.ndarray:
    """The difference of two Gumbel draws, the same for the same seed and step."""
    u = np.random.default_rng([seed, step]).uniform(1e-9, 1 - 1e-9, shape)
    return np.log(u) - np.log1p(-u)


def attention(qkv, spec: EncoderSpec):
    f, n, _ = value(qkv).shape
    h, dh = spec.heads, spec.dim // spec.heads
    x = transpose(reshape(qkv, (f, n, 3, h, dh)), (2, 0, 3, 1, 4))
    q, k, v = (take(x, i) for i in range(3))
    p = softmax(mul(matmul(q, transpose(k, (0, 1, 3, 2))), 1 / np.sqrt(dh)))
    return reshape(transpose(matmul(p, v), (0, 2, 1, 3)), (f, n, spec.dim)), value(p)[:, :, 0].mean(1)


def group_loss(raw: np.ndarray, refs: list[tuple[int, int]], ftype: np.ndarray, spec: EncoderSpec, params: list[dict[str, Var]], exact: np.ndarray, tau: float, noise: np.ndarray | None, r_target: float, alpha: float, cos_target: float | None = None, calibrator: bool = True):
    """(loss, mean cosine, soft reuse) of groups raw (G, frames, N, in_dim) whose frames refer to (past, future) places in the group or -1.

    noise (layers, frames, G, N) is None for hard decisions, as at inference.
    """
    w = kernel.weights_of(spec)
    groups, frames, n, d = raw.shape[0], raw.shape[1], spec.n_tokens, spec.dim
    x = [Var(kernel.embed(raw[:, f], spec)) for f in range(frames)]
    qkv = [matmul(norm(a), w["qkv"][0]) for a in x]
    soft = []
    for layer in range(spec.layers):
        last = layer + 1 == spec.layers
        p = params[layer]
        cache: list = []
        for f in range(frames):
            mixed, t = attention(qkv[f], spec)
            h = add(x[f], matmul(mixed, w["out"][layer]))
            ff = matmul(gelu(matmul(norm(h), w["up"][layer])), w["down"][layer])
            q = None if last else matmul(norm(add(h, ff)), w["qkv"][layer + 1])
            a, b = refs[f]
            if a >= 0 or b >= 0:
                sims = [kernel.cosine(value(h), value(cache_at(cache, r)[0])) if r >= 0 else np.full((groups, n), -1.0) for r in (a, b)]
                ahead = sims[1] > sims[0] + kernel.TIE
                pick = lambda i: mix(ahead, cache_at(cache, a)[i] if a >= 0 else None, cache_at(cache, b)[i] if b >= 0 else None)  # noqa: B023, E731
                rf, rq = pick(1), None if last else pick(2)
                if calibrator:
                    delta = add(h, mul(pick(0), -1.0))
                    more = add(matmul(relu(add(matmul(delta, p["c1"]), p["cb1"])), p["c2"]), p["cb2"])
                    rf, rq = (add(rf, more), None) if last else (rf, add(rq, more))
                hints = [kernel.codec_hints(raw[:, f], raw[:, r]) if r >= 0 else (np.zeros((groups, n)),) * 2 for r in (a, b)]
                motion, residual = (np.where(ahead, hints[1][i], hints[0][i]) for i in range(2))
                kind = np.where(ahead, ftype[max(b, 0)], ftype[max(a, 0)])
                own = np.full((groups, n), ftype[f]) if len(value(p["g1"])) > kernel.INPUTS else None
                v = kernel.gate_features(np.maximum(*sims), t, kind, motion, residual, own=own)
                logit = take(add(matmul(relu(add(matmul(v, p["g1"]), p["gb1"])), p["g2"]), p["gb2"]), (..., 0))
                body = np.ones((1, n))
                body[0, 0] = 0  # the class token is always computed
                m = mul(sigmoid(mul(add(logit, noise[layer, f]), 1 / tau)), body) if noise is not None else Var((value(logit) > 0) * body)
                soft.append(take(m, (slice(None), slice(1, None))))
                m3 = reshape(m, (groups, n, 1))
                rest = add(mul(m3, -1.0), 1.0)
                ff = add(mul(m3, rf), mul(rest, ff))
                if not last:
                    q = add(mul(m3, rq), mul(rest, q))
            cache.append((h, ff, q))
            x[f] = add(h, ff)
            if not last:
                qkv[f] = q
    total_cos, n_ref = None, 0
    for f in range(frames):
        if max(refs[f]) >= 0:
            c = mean(cosine_to(take(norm(x[f]), (slice(None), 0)), exact[:, f]))
            total_cos = c if total_cos is None else add(total_cos, c)
            n_ref += 1
    cos = mul(total_cos, 1 / n_ref)
    rate = mean(concat([reshape(s, (-1,)) for s in soft], 0))
    if cos_target is not None:  # as much reuse as a similarity allows
        short = cos_target - cos.v
        loss = add(mul(rate, -1.0), mul(add(mul(cos, -1.0), cos_target), alpha if short > 0 else 0.0))
    else:
        short = r_target - rate.v
        loss = add(add(mul(cos, -1.0), 1.0), mul(add(mul(rate, -1.0), r_target), alpha if short > 0 else 0.0))
    return loss, float(cos.v), float(rate.v)


def cache_at(cache: list, r: int):
    return cache[r]


def mix(ahead: np.ndarray, a, b):
    """Token by token, b where `ahead`, else a."""
    if b is None:
        return a
    if a is None:
        return b
    m = ahead[..., None].astype(float)
    return add(mul(a, 1 - m), mul(b, m))


def group_refs(segments: int, scheme: str = "reordered") -> tuple[list[int], list[tuple[int, int]], np.ndarray]:
    """(frame offsets, references as places in the group, frame types) of a group, in the order in which its frames are encoded.

    Reordered: the anchors of `segments` segments, then a B2 and a B1 frame of the last one. Sequential: segments + 3 frames in a row.
    segments = 0 is frame-wise: each frame refers to frames encoded in full, so no error is carried on.
    """
    if scheme == "sequential":
        n = segments + 3 if segments else 2
        return list(range(n)), [(i - 1, -1) for i in range(n)], np.array([0] + [1] * (n - 1))
    if not segments:
        return [0, 4, 2], [(-1, -1), (-1, -1), (0, 1)], np.array([0, 0, 2])
    g = 4 * segments
    offsets = [4 * i for i in range(segments + 1)] + [g - 2, g - 1]
    refs = [(i - 1, -1) for i in range(segments + 1)] + [(segments - 1, segments), (segments + 1, segments)]
    return offsets, refs, np.array([0] + [1] * segments + [2, 3])


#: Of a thousand videos so many are for training; the others are held out.
TRAIN_PER_MILLE = 600


def is_train(video_id="video_id"):
    """Whether a video may be learned from: by a hash of its id, so whole videos are on one side."""
    return F.pmod(F.xxhash64(F.lit("split"), F.col(video_id).cast("bigint")), F.lit(1000)) < TRAIN_PER_MILLE


def whole_groups(frames: DataFrame, spec: EncoderSpec, segments: int, reset_every: int = 20, scheme: str = "reordered") -> DataFrame:
    """(video_id, e, m: tokens by place) of every epoch of a training video that has all frames of a group."""
    offsets, _, _ = group_refs(segments, scheme)
    pos = F.pmod(F.col("frame_no") - 1, F.lit(reset_every))
    x = frames.where(is_train()).select("video_id", F.floor((F.col("frame_no") - 1) / reset_every).alias("e"), pos.alias("pos"), "tokens").where(F.col("pos").isin(offsets))
    return x.groupBy("video_id", "e").agg(F.map_from_entries(F.collect_list(F.struct("pos", "tokens"))).alias("m"), F.count(F.lit(1)).alias("n")).where(F.col("n") == len(offsets)).drop("n")


def sample_groups(frames: DataFrame, spec: EncoderSpec, segments: int, most: int, reset_every: int = 20, scheme: str = "reordered") -> np.ndarray:
    """(groups, frames, N, in_dim) of at most `most` groups from whole training videos; `most` bounds what reaches the driver."""
    offsets, _, _ = group_refs(segments, scheme)
    rows = whole_groups(frames, spec, segments, reset_every, scheme).orderBy(F.xxhash64("video_id", "e")).limit(most).collect()
    return np.array([[np.reshape(r["m"][o], (spec.n_tokens, spec.in_dim)) for o in offsets] for r in rows])


def adam(values: list[np.ndarray], grads: list, m1: list, m2: list, step: int, rate: float) -> None:
    """One step on the values, in place."""
    for i, g in enumerate(grads):
        m1[i] = 0.9 * m1[i] + 0.1 * g
        m2[i] = 0.99 * m2[i] + 0.01 * g * g
        values[i] -= rate * (m1[i] / (1 - 0.9**step)) / (np.sqrt(m2[i] / (1 - 0.99**step)) + 1e-8)


def fit_reuse(groups: np.ndarray, spec: EncoderSpec, r_target: float = 0.6, alpha: float = 1.0, steps: int = 120, rate: float = 0.01, segments: int = 3, seed: int = 5, batch: int = 64, tau: tuple[float, float] = (5.0, 0.2), cos_target: float | None = None, scheme: str = "reordered", calibrator: bool = True, own_type: bool = False) -> tuple[list[dict], list[tuple]]:
    """(modules, log of (step, loss, cosine, soft reuse, temperature)): Adam on the gates and calibrators alone."""
    _, refs, ftype = group_refs(segments, scheme)
    exact = np.array([kernel.exact(g, spec) for g in groups])
    params = [{k: Var(v) for k, v in m.items()} for m in kernel.new_modules(spec, seed, own_type=own_type)]
    flat = [v for p in params for v in p.values()]
    m1, m2, log = [np.zeros_like(v.v) for v in flat], [np.zeros_like(v.v) for v in flat], []
    rnd = np.random.default_rng(seed)
    for step in range(1, steps + 1):
        pick = rnd.choice(len(groups), min(batch, len(groups)), replace=False)
        t = tau[0] * (tau[1] / tau[0]) ** (step / steps)
        noise = gumbel(seed, step, (spec.layers, groups.shape[1], len(pick), spec.n_tokens))
        loss, cos, reuse = group_loss(groups[pick], refs, ftype, spec, params, exact[pick], t, noise, r_target, alpha, cos_target, calibrator=calibrator)
        for v in flat:
            v.g = None
        backward(loss)
        adam([v.v for v in flat], [v.g if v.g is not None else 0.0 for v in flat], m1, m2, step, rate)
        log.append((step, float(loss.v), cos, reuse, t))
    return [{k: v.v for k, v in p.items()} for p in params], log


def gradients(groups: np.ndarray, keys: list[tuple[int, int]], spec: EncoderSpec, modules: list[dict], tau: float, seed: int, step: int, segments: int = 3, scheme: str = "reordered", calibrator: bool = True) -> tuple[float, float, np.ndarray, np.ndarray]:
    """Sums over the groups: cosine, soft reuse, and the gradients of minus either by all weights in one vector.

    A group's noise comes from its key (video, epoch), so sums do not depend on how groups are split, and a repeated task gives the same.
    """
    _, refs, ftype = group_refs(segments, scheme)
    exact = np.array([kernel.exact(g, spec) for g in groups])
    draw = [np.random.default_rng([seed, step, *(k % 2**63 for k in key)]).uniform(1e-9, 1 - 1e-9, (spec.layers, groups.shape[1], spec.n_tokens)) for key in keys]
    u = np.stack(draw, 2)
    noise = np.log(u) - np.log1p(-u)
    found = []
    for alpha in (0.0, 1.0):  # without and with minus the reuse, which a target out of reach keeps in the loss
        params = [{k: Var(v) for k, v in m.items()} for m in modules]
        loss, cos, reuse = group_loss(groups, refs, ftype, spec, params, exact, tau, noise, 2.0, alpha, calibrator=calibrator)
        backward(loss)
        found.append(np.concatenate([(v.g if v.g is not None else np.zeros_like(v.v)).ravel() for p in params for v in p.values()]))
    n = len(groups)
    return cos * n, reuse * n, found[0] * n, (found[1] - found[0]) * n


def fit_reuse_distributed(frames: DataFrame, spec: EncoderSpec, r_target: float = 0.6, alpha: float = 1.0, steps: int = 120, rate: float = 0.01, segments: int = 3, seed: int = 5, share: float = 1.0, tau: tuple[float, float] = (5.0, 0.2), cos_target: float | None = None, scheme: str = "reordered", calibrator: bool = True, reset_every: int = 20, partitions: int | None = None, at_once: int = 64, own_type: bool = False) -> tuple[list[dict], list[tuple]]:
    """fit_reuse over every training group of the table, or each step over a hashed `share` of them: tasks send sums of gradients.

    Groups are written once. Of each step the driver gets one number pair for each weight, whatever the number of groups. Log as of fit_reuse.
    """
    import pyarrow as pa

    from .encode import encode_partitions, ship
    from .store import written

    spark = frames.sparkSession
    ship(spark)
    offsets, _, _ = group_refs(segments, scheme)
    tokens = F.array(*[F.element_at("m", F.lit(o).cast("int")) for o in offsets])
    rows = whole_groups(frames, spec, segments, reset_every, scheme).select(F.col("video_id").cast("bigint").alias("video_id"), F.col("e").cast("bigint").alias("e"), F.flatten(tokens).alias("raw"))
    rows = written(rows, "groups").repartition(partitions or encode_partitions(frames), "video_id", "e").sortWithinPartitions("video_id", "e")
    rows = written(rows, "dealt-groups")
    if rows.isEmpty():
        raise ValueError("no whole group of frames to learn from")
    modules = kernel.new_modules(spec, seed, own_type=own_type)
    flat = [v for m in modules for v in m.values()]
    cuts = np.cumsum([v.size for v in flat])[:-1]
    m1, m2, log = [np.zeros_like(v) for v in flat], [np.zeros_like(v) for v in flat], []
    for step in range(1, steps + 1):
        t = tau[0] * (tau[1] / tau[0]) ** (step / steps)
        sent = spark.sparkContext.broadcast(modules)

        def sums(batches, sent=sent, t=t, step=step):
            total = None
            for b in batches:
                for at in range(0, b.num_rows, at_once):
                    x = b.slice(at, at_once)
                    keys = list(zip(x.column("video_id").to_pylist(), x.column("e").to_pylist(), strict=True))
                    raw = np.array(x.column("raw").to_pylist(), float).reshape(len(keys), len(offsets), spec.n_tokens, spec.in_dim)
                    cos, reuse, g_cos, g_reuse = gradients(raw, keys, spec, sent.value, t, seed, step, segments, scheme, calibrator)
                    part = np.stack([np.append(g_cos, [cos, len(keys)]), np.append(g_reuse, [reuse, len(keys)])])
                    total = part if total is None else total + part
            if total is not None:
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(total.shape[1])), pa.array(total[0]), pa.array(total[1])], ["i", "a", "b"])

        taken = rows if share >= 1 else rows.where(F.pmod(F.xxhash64(F.lit(seed), F.lit(step), "video_id", "e"), F.lit(1_000_000)) < int(share * 1_000_000))
        got = taken.mapInArrow(sums, "i bigint, a double, b double").groupBy("i").agg(F.sum("a").alias("a"), F.sum("b").alias("b")).collect()
        sent.unpersist()
        if not got:  # no group in this step's share
            continue
        x = np.array([(r["a"], r["b"]) for r in sorted(got, key=lambda r: r["i"])]).T
        x = x[:, :-1] / x[0, -1]
        cos, reuse = x[:, -1]
        if cos_target is None:
            short, grad = r_target - reuse, x[0, :-1] + (alpha if reuse < r_target else 0.0) * x[1, :-1]
            loss = 1 - cos + alpha * max(short, 0.0)
        else:
            short, grad = cos_target - cos, x[1, :-1] + (alpha if cos < cos_target else 0.0) * x[0, :-1]
            loss = -reuse + alpha * max(short, 0.0)
        adam(flat, [g.reshape(v.shape) for g, v in zip(np.split(grad, cuts), flat, strict=True)], m1, m2, step, rate)
        log.append((step, float(loss), float(cos), float(reuse), t))
    return modules, log


def sweep(groups: np.ndarray, spec: EncoderSpec, r_targets: list[float], **options) -> dict[float, tuple[list[dict], list[tuple]]]:
    """A fit for each target: points of the trade-off."""
    return {r: fit_reuse(groups, spec, r, **options) for r in r_targets}


def sample_epochs(frames: DataFrame, spec: EncoderSpec, reset_every: int = 20, most: int = 48) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(epoch, frame number, whether it is the next epoch's first frame, raw tokens) of at most `most` whole epochs of training videos, in order."""
    e = F.floor((F.col("frame_no") - 1) / reset_every)
    x = frames.where(is_train()).select("video_id", e.alias("e"), "frame_no", "tokens")
    chosen = x.select("video_id", "e").distinct().orderBy(F.xxhash64("video_id", "e"), "video_id", "e").limit(most)
    first = F.pmod(F.col("frame_no") - 1, F.lit(reset_every)) == 0
    own = x.join(F.broadcast(chosen), ["video_id", "e"]).withColumn("halo", F.lit(False))
    after = x.where(first & (F.col("e") > 0)).withColumn("e", F.col("e") - 1).join(F.broadcast(chosen), ["video_id", "e"]).withColumn("halo", F.lit(True))
    rows = sorted(own.unionByName(after).collect(), key=lambda r: (r["video_id"], r["e"], r["frame_no"]))
    keys = {k: i for i, k in enumerate(dict.fromkeys((r["video_id"], r["e"]) for r in rows))}
    raw = np.array([np.reshape(r["tokens"], (spec.n_tokens, spec.in_dim)) for r in rows]).reshape(-1, spec.n_tokens, spec.in_dim)
    return np.array([keys[r["video_id"], r["e"]] for r in rows], np.int64), np.array([r["frame_no"] for r in rows], np.int64), np.array([r["halo"] for r in rows], bool), raw


def at_reuse(epochs: tuple, spec: EncoderSpec, cfg, modules: list[dict] | None, rho: float, rounds: int = 14):
    """cfg moved along its own trade-off until the sampled epochs reuse the share rho of their tokens: by the learned gate's shift or the fixed gate's threshold."""
    from dataclasses import replace

    from ..plans.reference import epoch_plan

    part, no, halo, raw = epochs
    if not len(raw):
        return cfg
    last = np.zeros(part.max() + 1, np.int64)
    np.maximum.at(last, part, no)
    kind, wave, _, *refs = epoch_plan(no, last[part], cfg.scheme, cfg.reset_every, cfg.tail, cfg.lookback)
    kind, wave, *refs = (np.where(halo, 0, x) for x in (kind, wave, *refs))
    past, future, *more = kernel.rows_of(no, part, *refs)
    lo, hi = (-60.0, 60.0) if cfg.gate == "learned" else (-12.0, 6.0)
    made = lambda v: replace(cfg, shift=v) if cfg.gate == "learned" else replace(cfg, theta=float(np.exp(v)))
    for _ in range(rounds):
        mid = (lo + hi) / 2
        got = kernel.gated(raw, past, future, kind, wave, spec, made(mid), modules, more=tuple(more)).reuse[~halo][:, :, 1:].mean()
        lo, hi = (mid, hi) if got < rho else (lo, mid)
    return made((lo + hi) / 2)
