"""Encoder shapes, options of reuse, and the schemas that go between the parts."""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np

FRAMES = "video_id bigint, frame_no int, tokens array<double>"
EMBEDDINGS = "video_id bigint, frame_no int, emb array<double>, reuse_rate double, flops double"
TYPES = ("I", "P", "B2", "B1")


@dataclass(frozen=True)
class EncoderSpec:
    """layers, width, heads, tokens per frame (class token included), values per raw token."""

    layers: int = 2
    dim: int = 16
    heads: int = 2
    n_tokens: int = 6
    in_dim: int = 12
    seed: int = 0
    ffn_mult: int = 4

    @property
    def hidden(self) -> int:
        """Width of the calibrator: an eighth of the encoder's, 128 at 1024."""
        return max(4, self.dim // 8)

    @staticmethod
    def preset(name: str, **other) -> EncoderSpec:
        shapes = {"small": (12, 384, 6), "base": (12, 768, 12), "large": (24, 1024, 16), "tiny": (2, 16, 2), "deep": (4, 32, 4), "bench": (4, 128, 4)}
        layers, dim, heads = shapes[name]
        spec = EncoderSpec(layers, dim, heads)
        if name in ("small", "base", "large"):
            spec = replace(spec, n_tokens=257, in_dim=768)
        return replace(spec, **other)


@dataclass(frozen=True)
class ReuseConfig:
    """How frames refer to each other, which gate decides, and how the work is scheduled."""

    scheme: str = "reordered"  # or sequential
    reset_every: int = 20
    tail: str = "chain"  # short_anchor, recompute
    lookback: int = 1  # past references of the sequential scheme
    gate: str = "learned"  # mse, budget, never, always
    theta: float = 0.1
    budget: int = 2
    reference: str = "previous"  # of the budget gate; or last_fresh
    features: str = "strc"  # of the learned gate: similarity, importance, reference type, codec hints
    own_type: bool = False  # the learned gate also sees the type of its own frame; trained weights say so themselves
    calibrator: bool = True
    residual: str = "current"  # or cached
    schedule: str = "layer"  # or frame
    compaction: str = "batch"  # frame, none
    free_cache: bool = True
    batch_epochs: int = 64  # at most, and as many as batch_bytes hold
    batch_bytes: int = 256 << 20
    shift: float = 0.0  # added to the learned gate's logit: moves along the trade-off

    def epochs_at_once(self, spec: EncoderSpec) -> int:
        """Epochs of a batch: batch_epochs, fewer where their tokens and one layer's caches would pass batch_bytes."""
        frame = spec.n_tokens * 8 * (spec.in_dim + 8 * spec.dim)
        return max(1, min(self.batch_epochs, self.batch_bytes // (frame * (self.reset_every + 1))))


def closed_form(layer: int, part: int, rows: int, cols: int, seed: int = 0) -> np.ndarray:
    """A frozen weight matrix from integers alone, so that any engine can build the same."""
    i, j = np.arange(rows)[:, None], np.arange(cols)[None, :]
    n = (7919 * i + 104729 * j + 1299709 * layer + 15485863 * part + (31 * i + 17 * j) ** 2 + 6700417 * seed) % 2003
    return (n / 2003 - 0.5) * np.sqrt(12 / rows)


def backbone(spec: EncoderSpec) -> dict:
    """The frozen weights."""
    d, m = spec.dim, spec.ffn_mult * spec.dim
    make = lambda layer, part, r, c: closed_form(layer, part, r, c, spec.seed)
    return {
        "embed": make(0, 0, spec.in_dim, d),
        "pos": 0.5 * make(0, 1, spec.n_tokens, d) * np.sqrt(spec.n_tokens),
        "qkv": [make(n, 2, d, 3 * d) for n in range(spec.layers)],
        "out": [make(n, 3, d, d) for n in range(spec.layers)],
        "up": [make(n, 4, d, m) for n in range(spec.layers)],
        "down": [make(n, 5, m, d) for n in range(spec.layers)],
    }
