"""The numpy kernel: exact and gated encoding of a batch of epochs, in any schedule and compaction, with what it cost.

Frames of all epochs of a batch are rows of one array. Within a layer, frames whose references are done form a wavefront; all of
them, over all epochs, go through one multiply. The reused unit is the token-wise chain after a layer's attention: the
feed-forward branch and the next layer's QKV.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass, field

import numpy as np

from ..model import TYPES, EncoderSpec, ReuseConfig, backbone

_WEIGHTS: dict = {}
#: Similarities no further apart are equal, or round-off would choose between references of the same content.
TIE = 1e-9
#: Inputs of a gate; one that also sees the type of its own frame has four more, and is known by that.
INPUTS = 8
#: Numbers that go through an elementwise function at once.
PIECE = 1 << 15


def weights_of(spec: EncoderSpec) -> dict:
    if spec not in _WEIGHTS:
        _WEIGHTS.clear()
        _WEIGHTS[spec] = backbone(spec)
    return _WEIGHTS[spec]


def norm(x: np.ndarray) -> np.ndarray:
    c = x - x.mean(-1, keepdims=True)
    return c / np.sqrt((c * c).mean(-1, keepdims=True) + 1e-6)


def gelu(x: np.ndarray) -> np.ndarray:
    """x / 2 (1 + tanh y) as x / (1 + exp(-2y)), in place and in pieces that stay in the cache."""
    out = np.empty(x.shape)
    rows, to = x.reshape(-1, x.shape[-1]), out.reshape(-1, x.shape[-1])
    step = max(1, PIECE // max(1, x.shape[-1]))
    with np.errstate(over="ignore"):
        for at in range(0, len(rows), step):
            v, y = rows[at : at + step], to[at : at + step]
            np.multiply(v, v, out=y)
            y *= v
            y *= 0.044715
            y += v
            y *= -2 * 0.7978845608028654
            np.exp(y, out=y)
            y += 1
            np.divide(v, y, out=y)
    return out


def times(x: np.ndarray, w: np.ndarray) -> np.ndarray:
    """x @ w as one multiply of all rows."""
    return (x.reshape(-1, x.shape[-1]) @ w).reshape(*x.shape[:-1], w.shape[-1])


def cosine(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Along the last axis; 0 where a vector is zero."""
    n = np.linalg.norm(a, axis=-1) * np.linalg.norm(b, axis=-1)
    return np.divide((a * b).sum(-1), n, out=np.zeros(n.shape), where=n > 0)


def attention(qkv: np.ndarray, spec: EncoderSpec) -> tuple[np.ndarray, np.ndarray]:
    """(mixed values (F, N, D), the class token's attention to each token, mean of the heads (F, N))."""
    f, n, _ = qkv.shape
    h, dh = spec.heads, spec.dim // spec.heads
    q, k, v = qkv.reshape(f, n, 3, h, dh).transpose(2, 0, 3, 1, 4)
    s = q @ k.transpose(0, 1, 3, 2) / np.sqrt(dh)
    s = np.exp(s - s.max(-1, keepdims=True))
    s /= s.sum(-1, keepdims=True)
    return (s @ v).transpose(0, 2, 1, 3).reshape(f, n, spec.dim), s[:, :, 0].mean(1)


def embed(raw: np.ndarray, spec: EncoderSpec) -> np.ndarray:
    w = weights_of(spec)
    return times(raw, w["embed"]) + w["pos"]


def start(raw: np.ndarray, spec: EncoderSpec) -> tuple[np.ndarray, np.ndarray]:
    """(inputs of the first layer's unit, the class token's attention): the first layer's attention, which no gate touches and all ways share."""
    w, x = weights_of(spec), embed(raw, spec)
    mixed, t = attention(times(norm(x), w["qkv"][0]), spec)
    return x + times(mixed, w["out"][0]), t


def unit(x: np.ndarray, layer: int, spec: EncoderSpec) -> tuple[np.ndarray, np.ndarray | None]:
    """(feed-forward branch, next layer's QKV or None) of rows x. Rows of a stack are multiplied a part of the stack at a time."""
    w = weights_of(spec)
    f = gelu(norm(x) @ w["up"][layer]) @ w["down"][layer]
    return f, norm(x + f) @ w["qkv"][layer + 1] if layer + 1 < spec.layers else None


def exact(raw: np.ndarray, spec: EncoderSpec, begun: tuple[np.ndarray, np.ndarray] | None = None) -> np.ndarray:
    """Embeddings (F, D) of raw tokens (F, N, in_dim) by the unmodified encoder; begun is their `start`."""
    w = weights_of(spec)
    x, _ = begun or start(raw, spec)
    for layer in range(spec.layers):
        if layer:
            x = x + times(attention(qkv, spec)[0], w["out"][layer])  # noqa: F821
        f, qkv = unit(x.reshape(-1, spec.dim), layer, spec)
        x = x + f.reshape(x.shape)
        qkv = None if qkv is None else qkv.reshape(*x.shape[:2], -1)
    return norm(x[:, :1])[:, 0]


def codec_hints(raw: np.ndarray, ref: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(motion, residual) of tokens against a reference: the ring shift in -2..2 of least L1 distance, over 2; mean absolute change."""
    shifts = (0, 1, -1, 2, -2)
    dist = np.stack([np.abs(raw - np.roll(ref, s, -1)).sum(-1) for s in shifts])
    dist += np.arange(len(shifts)).reshape(-1, *[1] * (dist.ndim - 1)) * TIE / 8  # the least shift of equal ones
    return np.abs(np.array(shifts))[dist.argmin(0)] / 2, np.abs(raw - ref).mean(-1)


def new_modules(spec: EncoderSpec, seed: int = 1, hidden: int = 16, own_type: bool = False) -> list[dict]:
    """Untrained gate and calibrator weights of each layer: the gate leans on similarity, the calibrator adds nothing. With own_type the gate has four more inputs."""
    r = np.random.default_rng(seed)
    out = []
    for layer in range(spec.layers):
        wide = spec.dim * (3 if layer + 1 < spec.layers else 1)
        g1 = r.normal(size=(INPUTS + 4 * own_type, hidden)) * 0.3
        g1[0, 0] = 6.0
        b1 = np.zeros(hidden)
        b1[0] = -5.4
        g2 = r.normal(size=(hidden, 1)) * 0.05
        g2[0] = 4.0
        out.append({"g1": g1, "gb1": b1, "g2": g2, "gb2": np.array([-1.0]), "c1": r.normal(size=(spec.dim, spec.hidden)) / np.sqrt(spec.dim), "cb1": np.zeros(spec.hidden), "c2": np.zeros((spec.hidden, wide)), "cb2": np.zeros(wide)})
    return out


def calibrate(delta: np.ndarray, m: dict) -> np.ndarray:
    return np.maximum(delta @ m["c1"] + m["cb1"], 0) @ m["c2"] + m["cb2"]


def gate_features(s, t, ref_type, motion, residual, which: str = "strc", own=None) -> np.ndarray:
    """(…, 8): similarity, importance, one-hot reference type, motion and residual; dropped ones are 0. With own, the frames' types, (…, 12)."""
    one = np.eye(4)[ref_type]
    v = np.concatenate([s[..., None], t[..., None], one, motion[..., None], residual[..., None]], -1)
    keep = np.array([c in which for c in "strrrrcc"], float)
    v = v * keep
    return v if own is None else np.concatenate([v, np.broadcast_to(np.eye(4)[own], (*v.shape[:-1], 4))], -1)


def gate_logit(v: np.ndarray, m: dict) -> np.ndarray:
    return (np.maximum(v @ m["g1"] + m["gb1"], 0) @ m["g2"] + m["gb2"])[..., 0]


@dataclass
class Done:
    emb: np.ndarray
    reuse: np.ndarray  # (F, layers, N)
    count: Counter = field(default_factory=Counter)
    rows: list = field(default_factory=list)  # of each token-wise multiply
    trace: list = field(default_factory=list)  # live cached bytes after each step


def flops_exact(spec: EncoderSpec) -> int:
    """Of a frame, as published accounts do it: projections, attention, feed-forward at 4x."""
    n, d = spec.n_tokens, spec.dim
    return spec.layers * (n * 24 * d * d + 4 * n * n * d)


def flops_gated(spec: EncoderSpec, reused: np.ndarray, gate: str = "learned", calibrator: bool = True, refs: np.ndarray | int = 2, hidden: int = 16, inputs: int = INPUTS) -> np.ndarray:
    """Of frames with `reused` (F, layers) tokens and `refs` references each; frames without references have no gate."""
    n, d, total = spec.n_tokens, spec.dim, 6 * spec.n_tokens * spec.dim**2
    out = np.full(len(reused), float(total))
    refs = np.broadcast_to(refs, len(reused))
    gated = refs > 0
    for layer in range(spec.layers):
        r = reused[:, layer]
        per = 22 if layer + 1 < spec.layers else 16
        out += 4 * n * n * d + 2 * n * d * d + per * d * d * (n - r)
        wide = 3 * d if layer + 1 < spec.layers else d
        if gate == "learned":
            out += gated * (n - 1) * (2 * inputs * hidden + 2 * hidden + refs * 6 * d)
        elif gate in ("mse", "budget"):
            out += gated * (n - 1) * 3 * d
        if calibrator:
            out += r * 2 * spec.hidden * (d + wide)
    return out


def gated(raw: np.ndarray, past: np.ndarray, future: np.ndarray, ftype: np.ndarray, wave: np.ndarray, spec: EncoderSpec, cfg: ReuseConfig, modules: list[dict] | None = None, order: np.ndarray | None = None, more: tuple[np.ndarray, ...] = (), begun: tuple[np.ndarray, np.ndarray] | None = None, hints: list | None = None) -> Done:
    """Encode F frames; past and future are row numbers of references or -1, ftype numbers of TYPES, wave their wavefronts.

    order is the execution order for schedule "frame". With free_cache a frame's caches count as freed as soon as no later frame refers to
    them: `trace` has the live bytes after each step. more are further references (several past frames). begun is the frames' `start`; hints is a list
    that keeps what the gates of several runs with the same references see alike.

    In schedule "frame" each frame has multiplies of its own. Frames of a wavefront do not refer to each other, so their arrays are walked together.
    """
    w = weights_of(spec)
    f_all, n, d, layers = len(raw), spec.n_tokens, spec.dim, spec.layers
    begun = begun or start(raw, spec)
    reuse = np.zeros((f_all, layers, n), bool)
    done = Done(np.zeros((f_all, d)), reuse)
    done.count["attention"] = f_all  # of the first layer
    refs = (past, future, *more)
    referred = np.zeros(f_all, bool)
    for r in refs:
        referred[r[r >= 0]] = True
    slots = 1 if cfg.schedule == "layer" and cfg.free_cache else layers  # caches of one layer at a time, or of all of them where frames go one by one
    cache: list[dict] = [{} for _ in range(slots)]
    fresh_in: list[dict] = [dict() for _ in range(layers)]  # for the budget gate's last_fresh
    hints = [] if hints is None else hints
    per_frame = n * (d + d + 3 * d) * 8
    frame_by_frame = cfg.schedule != "layer"

    def arrays(layer, h=None):
        c = cache[layer % slots]
        if c.get("layer") != layer:
            wide = 3 * d if layer + 1 < layers else 0
            c.clear()
            c.update(layer=layer, h=np.empty((f_all, n, d)) if h is None else h, f=np.empty((f_all, n, d)), q=np.empty((f_all, n, wide)), size=np.zeros((f_all, n)))
        return c

    def likeness(h, size, c, r):
        """Cosines of tokens to those of the reference frames r; -1 without one."""
        at = np.maximum(r, 0)
        both = size * c["size"][at]
        dots = np.einsum("fnd,fnd->fn", h, c["h"][at])
        return np.where((r >= 0)[:, None], np.divide(dots, both, out=np.zeros_like(dots), where=both > 0), -1.0)

    def decide(layer, idx, h, t, c):
        """(mask (frames, tokens), row of the chosen reference (frames, tokens))."""
        mine = [r[idx] for r in refs]
        size = c["size"][idx]
        best, ref, which = likeness(h, size, c, mine[0]), np.repeat(mine[0][:, None], n, 1), np.zeros((len(idx), n), np.int64)
        for k, r in enumerate(mine[1:], 1):
            if (r >= 0).any():
                s = likeness(h, size, c, r)
                ahead = s > best + TIE  # of equal similarities the one before stays: past before future
                best, ref, which = np.where(ahead, s, best), np.where(ahead, r[:, None], ref), np.where(ahead, k, which)
        any_ref = (np.stack(mine) >= 0).any(0)[:, None]
        token = np.arange(n)[None, :]
        if cfg.gate == "always":
            mask = np.ones(best.shape, bool)
        elif cfg.gate == "mse":
            mask = ((h - c["h"][np.maximum(ref, 0), token]) ** 2).mean(-1) < cfg.theta
        elif cfg.gate == "budget":
            base = c["h"][np.maximum(ref, 0), token]
            if cfg.reference == "last_fresh":
                base = np.stack([fresh_in[layer].get(int(r), base[k]) for k, r in enumerate(np.maximum(mine[0], 0))])
            change = ((h - base) ** 2).mean(-1)
            change[:, 0] = np.inf  # the class token is always computed and is not part of the budget
            rank = np.argsort(np.argsort(-change, axis=1, kind="stable"), axis=1)
            mask = rank > cfg.budget
        else:
            if not hints:
                hints.extend(codec_hints(raw, raw[np.maximum(r, 0)]) for r in refs)
            motion, residual = (np.select([which == k for k in range(len(refs))], [hints[k][i][idx] for k in range(len(refs))]) for i in (0, 1))
            own = ftype[idx][:, None] if len(modules[layer]["g1"]) > INPUTS else None
            v = gate_features(best, t, ftype[np.maximum(ref, 0)], motion, residual, cfg.features, own)
            mask = gate_logit(v, modules[layer]) + cfg.shift > 0
        mask = mask & any_ref
        mask[:, 0] = False
        return mask, ref

    def multiply(rows, layer):
        each, n_rows = (1, len(rows)) if rows.ndim == 2 else rows.shape[:2]
        done.count["multiplies"] += each
        done.count["rows"] += each * n_rows
        done.rows.extend([n_rows] * each)
        return unit(rows, layer, spec)

    def work(layer, idx, h, t, c):
        """The reuse unit of the frames idx with unit inputs h; the results go to the layer's cache."""
        last = layer + 1 == layers
        flat_f, flat_q, flat_h = c["f"].reshape(-1, d), c["q"].reshape(f_all * n, -1), c["h"].reshape(-1, d)
        if cfg.gate == "never" or not any((r[idx] >= 0).any() for r in refs):
            mask, ref = np.zeros((len(idx), n), bool), None
        else:
            mask, ref = decide(layer, idx, h, t, c)
        if cfg.compaction != "frame" and not frame_by_frame:
            i, j = np.nonzero(~mask if cfg.compaction == "batch" else np.ones_like(mask))
            groups = [idx[i] * n + j]
        else:  # stacks of frames with as many active tokens
            active = ~mask if cfg.compaction != "none" else np.ones_like(mask)
            size = active.sum(1)
            i, j = np.nonzero(active)
            groups = [(idx[i] * n + j)[np.repeat(size == k, size)].reshape(-1, k) for k in np.unique(size[size > 0])]
        for g in groups:
            if len(g):
                ff, qq = multiply(flat_h[g], layer)
                flat_f[g] = ff
                if not last:
                    flat_q[g] = qq
        i, j = np.nonzero(mask)
        if len(i):
            to, source = idx[i] * n + j, ref[i, j] * n + j
            reused_f = flat_f[source]
            delta = flat_h[to] - flat_h[source] if cfg.residual == "cached" or (cfg.calibrator and modules is not None) else None
            if cfg.residual == "cached":
                reused_f = reused_f - delta
            extra = calibrate(delta, modules[layer]) if cfg.calibrator and modules is not None else None
            flat_f[to] = reused_f if extra is None or not last else reused_f + extra
            if not last:
                flat_q[to] = flat_q[source] if extra is None else flat_q[source] + extra
        if cfg.reference == "last_fresh":
            for k, row in enumerate(idx):
                base = fresh_in[layer].get(int(max(past[row], 0)), h[k])
                fresh_in[layer][int(row)] = np.where(mask[k][:, None], base, h[k])
        reuse[idx, layer] = mask

    def attend(layer, x, qkv):
        done.count["attention"] += len(x)
        mixed, t = attention(qkv, spec)
        return x + times(mixed, w["out"][layer]), t

    live = 0
    place = np.unique(wave, return_inverse=True)[1]
    waves = [np.flatnonzero(place == k) for k in range(int(place.max(initial=-1)) + 1)]
    if not frame_by_frame:
        ends = _last_uses(place, refs)
        for layer in range(layers):
            h, t = attend(layer, x, qkv) if layer else begun  # noqa: F821
            c = arrays(layer, h)
            c["size"] = np.sqrt(np.einsum("fnd,fnd->fn", h, h))
            for k, idx in enumerate(waves):
                work(layer, idx, h if len(idx) == f_all else h[idx], t[idx], c)
                live += len(idx) * per_frame
                done.trace.append((layer, k, live))
                if cfg.free_cache:
                    live -= int((ends == k).sum()) * per_frame  # nobody refers to these any more
                    done.trace.append((layer, k, live))
            x, qkv = h + c["f"], c["q"]  # noqa: F841
            if cfg.free_cache:
                live = 0
                done.trace.append((layer, -1, live))
        state_x = x
    else:
        state_x = np.empty((f_all, n, d))
        for idx in waves:
            for layer in range(layers):
                h, t = attend(layer, xr, qr) if layer else (begun[0][idx], begun[1][idx])  # noqa: F821
                c = arrays(layer)
                c["h"][idx], c["size"][idx] = h, np.sqrt(np.einsum("fnd,fnd->fn", h, h))
                work(layer, idx, h, t, c)
                xr, qr = h + c["f"][idx], c["q"][idx]
            state_x[idx] = xr
        steps = order if order is not None else np.lexsort((np.arange(f_all), wave))
        at = np.empty(f_all, np.int64)
        at[steps] = np.arange(f_all)
        gone = np.bincount(_last_uses(at, refs), minlength=f_all)
        for k, row in enumerate(steps.tolist()):
            for layer in range(layers):
                live += per_frame
                done.trace.append((layer, row, live))
            if cfg.free_cache:
                live -= int(gone[k]) * layers * per_frame
                done.trace.append((layers - 1, row, live))
    done.emb = norm(state_x[:, :1])[:, 0]
    done.count["reused"] = int(reuse.sum())
    done.count["peak"] = max((b for *_, b in done.trace), default=0)
    return done


def _last_uses(place: np.ndarray, refs) -> np.ndarray:
    """The step after which a frame's cache is not referred to any more (its own where nobody refers to it), of frames whose steps are `place`."""
    out = place.copy()
    for r in refs:
        np.maximum.at(out, r[r >= 0], place[r >= 0])
    return out


def _of_layer(count: int | tuple[int, ...], layer: int) -> int:
    return count[layer] if isinstance(count, tuple) else count


def reduced(raw: np.ndarray, spec: EncoderSpec, prune: int | tuple[int, ...] = 1, merge: int | tuple[int, ...] = 1, begun: tuple[np.ndarray, np.ndarray] | None = None) -> tuple[np.ndarray, float]:
    """In-frame reduction: in each layer the `prune` tokens of least class attention go and the `merge` most alike pairs become one.

    Either count may be one for each layer. (embeddings, FLOPs of a frame). Merged tokens are means weighted by how many tokens they stand for; the class token stays.
    """
    w = weights_of(spec)
    x, t = (begun[0].copy(), begun[1]) if begun else start(raw, spec)
    size = np.ones(x.shape[:2])
    d, flops = spec.dim, 0.0
    for layer in range(spec.layers):
        n = x.shape[1]
        if layer:
            mixed, t = attention(times(norm(x), w["qkv"][layer]), spec)
            x = x + times(mixed, w["out"][layer])
        flops += 6 * n * d * d + 4 * n * n * d + 2 * n * d * d
        p = min(_of_layer(prune, layer), n - 2)
        if p > 0:
            t = t.copy()
            t[:, 0] = np.inf
            keep = np.sort(np.argsort(-t, axis=1, kind="stable")[:, : n - p], axis=1)
            x, size = np.take_along_axis(x, keep[..., None], 1), np.take_along_axis(size, keep, 1)
        m = min(_of_layer(merge, layer), (x.shape[1] - 1) // 2)
        if m > 0:
            a, b = np.arange(1, x.shape[1], 2), np.arange(2, x.shape[1], 2)  # two sides of a bipartite matching
            if len(b):
                sim = cosine(x[:, a][:, :, None], x[:, b][:, None])
                best, to = sim.max(2), sim.argmax(2)
                m = min(m, len(a))
                pick = np.argsort(-best, axis=1, kind="stable")[:, :m]
                gone = np.zeros(x.shape[:2], bool)
                for k in range(m):
                    rows = np.arange(len(x))
                    i, j = a[pick[:, k]], b[to[rows, pick[:, k]]]
                    total = size[rows, i] + size[rows, j]
                    x[rows, j] = (x[rows, i] * size[rows, i, None] + x[rows, j] * size[rows, j, None]) / total[:, None]
                    size[rows, j] = total
                    gone[rows, i] = True
                left = x.shape[1] - m
                x, size = x[~gone].reshape(len(x), left, d), size[~gone].reshape(len(x), left)
        n = x.shape[1]
        f = times(gelu(times(norm(x), w["up"][layer])), w["down"][layer])
        x = x + f
        flops += 16 * n * d * d
    return norm(x)[:, 0], flops


def rows_of(frame_no: np.ndarray, epoch: np.ndarray, *refs: np.ndarray) -> tuple[np.ndarray, ...]:
    """Row numbers of references within a batch, from frame numbers; -1 where there is none. epoch numbers a batch's epochs; rows are in their order."""
    span = int(frame_no.max(initial=0)) + 2
    key = epoch.astype(np.int64) * span + frame_no
    out = []
    for r in refs:
        want = epoch.astype(np.int64) * span + r
        at = np.minimum(np.searchsorted(key, want), len(key) - 1)
        if not (key[at] == want)[r > 0].all():
            raise ValueError("a reference is not in its epoch: frame numbers have gaps")
        out.append(np.where(r > 0, at, -1))
    return tuple(out)


assert TYPES[0] == "I"
