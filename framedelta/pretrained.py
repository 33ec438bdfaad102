"""Trained gates and calibrators, by fixture. They are in weights.json beside this file, written by framedelta.train."""

from __future__ import annotations

import json
from functools import cache
from importlib import resources

import numpy as np


@cache
def modules(name: str) -> list[dict] | None:
    """Weights of each layer, or None where nothing was trained under the name."""
    text = resources.files(__package__).joinpath("weights.json").read_text()
    found = json.loads(text).get(name)
    return None if found is None else [{k: np.array(v) for k, v in layer.items()} for layer in found]


def names() -> list[str]:
    return sorted(json.loads(resources.files(__package__).joinpath("weights.json").read_text()))


def as_json(trained: dict[str, list[dict]]) -> str:
    return json.dumps({n: [{k: np.round(v, 5).tolist() for k, v in layer.items()} for layer in m] for n, m in trained.items()}, separators=(",", ":"))
