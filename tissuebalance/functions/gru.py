"""A gated recurrent cell shared by all boundaries, with a scalar head."""

from __future__ import annotations

import json
from importlib import resources

import numpy as np

from .balance import N_FEATURES

HIDDEN = 24
Weights = dict[str, np.ndarray]


def init(seed: int, inputs: int = N_FEATURES, hidden: int = HIDDEN) -> Weights:
    """Uniform weights and a head of zeros: untrained, the residual is 0 everywhere."""
    rng = np.random.default_rng(seed)
    k = hidden**-0.5
    return {
        "w_x": rng.uniform(-k, k, (inputs, 3 * hidden)), "w_h": rng.uniform(-k, k, (hidden, 3 * hidden)),
        "b_x": rng.uniform(-k, k, 3 * hidden), "b_h": rng.uniform(-k, k, 3 * hidden), "head": np.zeros((hidden, 1)), "bias": np.zeros(1),
    }


def size(w: Weights) -> int:
    return sum(v.size for v in w.values())


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-x))


def step(x: np.ndarray, h: np.ndarray, w: Weights) -> tuple[np.ndarray, np.ndarray]:
    """The next hidden state and the residual of each row."""
    n = h.shape[-1]
    a, b = x @ w["w_x"] + w["b_x"], h @ w["w_h"] + w["b_h"]
    reset, update = sigmoid(a[..., :n] + b[..., :n]), sigmoid(a[..., n : 2 * n] + b[..., n : 2 * n])
    fresh = np.tanh(a[..., 2 * n :] + reset * b[..., 2 * n :])
    h = (1 - update) * fresh + update * h
    return h, (h @ w["head"] + w["bias"])[..., 0]


def dumps(w: Weights, digits: int = 6) -> str:
    return json.dumps({k: {"shape": v.shape, "data": [round(float(x), digits) for x in v.ravel()]} for k, v in w.items()})


def loads(text: str) -> Weights:
    return {k: np.array(v["data"]).reshape(v["shape"]) for k, v in json.loads(text).items()}


def trained() -> Weights:
    """The weights shipped with the package."""
    return loads((resources.files("tissuebalance.functions") / "weights.json").read_text())
