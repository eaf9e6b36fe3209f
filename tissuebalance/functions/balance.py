"""Pure functions of boundary control, on arrays whose last axis is the boundary or the rank.

Boundary b lies between rank b and rank b + 1. A positive imbalance means that the right rank
is slower; the boundary index then grows and the left rank gains slices.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class Rule:
    """Tau and alpha of the reactive rule. The rest are our own choices."""

    tau: float = 0.02
    alpha: float = 0.5
    margin: float = 1e-6
    rounding: str = "half_away"
    mode: str = "guarded"


def ratio(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """a / b, and 0 where b is 0: an undefined ratio is no signal."""
    a, b = np.broadcast_arrays(np.asarray(a, float), np.asarray(b, float))
    return np.divide(a, b, out=np.zeros(a.shape), where=b != 0)


def local_imbalance(times: np.ndarray) -> np.ndarray:
    left, right = times[..., :-1], times[..., 1:]
    return ratio(right - left, (right + left) / 2)


def global_imbalance(times: np.ndarray) -> np.ndarray:
    return ratio(times.max(axis=-1) - times.min(axis=-1), times.mean(axis=-1))


def relative_excess(times: np.ndarray) -> np.ndarray:
    return ratio(times.max(axis=-1) - times.mean(axis=-1), times.mean(axis=-1))


def proposal(times: np.ndarray, widths: np.ndarray, rule: Rule = Rule()) -> np.ndarray:
    """Signed slices the reactive rule would move at each boundary."""
    left, right = times[..., :-1], times[..., 1:]
    gap = local_imbalance(times)
    slow_width = np.where(right > left, widths[..., 1:], widths[..., :-1])
    size = rule.alpha * slow_width * ratio(np.abs(right - left), 2 * np.maximum(left, right))
    return np.where(np.abs(gap) > rule.tau, np.sign(gap) * size, 0.0)


def combine(reactive: np.ndarray, residual: np.ndarray, most: float, rule: Rule = Rule()) -> np.ndarray:
    """The residual added in atanh space, so that the step stays within its bound."""
    inside = np.clip(np.asarray(reactive, float) / most, -1 + rule.margin, 1 - rule.margin)
    return most * np.tanh(np.arctanh(inside) + residual)


def guard(step: np.ndarray, gap: np.ndarray, mode: str = "guarded") -> np.ndarray:
    """guarded: a step away from the slower rank is no step."""
    return np.where(step * gap > 0, step, 0.0) if mode == "guarded" else step


def whole(step: np.ndarray, rounding: str = "half_away", carried: np.ndarray | float = 0.0) -> tuple[np.ndarray, np.ndarray]:
    """Whole slices and what is carried to the next event (only 'carry' keeps fractions)."""
    step = np.asarray(step, float) + carried
    if rounding == "floor":
        return (np.sign(step) * np.floor(np.abs(step))).astype(int), np.zeros_like(step)
    out = (np.sign(step) * np.floor(np.abs(step) + 0.5)).astype(int) if rounding == "half_away" else np.trunc(step + np.sign(step) * 1e-12).astype(int)
    return out, step - out if rounding == "carry" else np.zeros_like(step)


def sweep(bounds: np.ndarray, steps: np.ndarray, least: int) -> np.ndarray:
    """All steps in one pass from the left; none may leave a rank narrower than least."""
    out = np.array(bounds)
    for b in range(1, len(bounds) - 1):
        out[b] = min(max(bounds[b] + steps[b - 1], out[b - 1] + least), bounds[b + 1] - least)
    return out


def rank_times(load: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    upto = np.concatenate([[0.0], np.cumsum(load)])
    return np.diff(upto[np.asarray(bounds)])


def holt(level: np.ndarray, trend: np.ndarray, x: np.ndarray, a: float = 0.5, b: float = 0.3) -> tuple[np.ndarray, np.ndarray]:
    new = a * x + (1 - a) * (level + trend)
    return new, b * (new - level) + (1 - b) * trend


N_FEATURES = 12


def features(times, widths, before, moved, reactive, phase, grew, m: int, ranks: int, least: int, most: float) -> np.ndarray:
    """Twelve clamped, dimensionless numbers for each boundary."""
    gap = local_imbalance(times)
    even = m / ranks
    room = (widths - least) / even
    spread = np.broadcast_to(np.asarray(global_imbalance(times))[..., None], gap.shape)
    columns = [
        np.clip(gap, -2, 2), np.clip(gap - before, -2, 2), np.clip(spread, 0, 4),
        np.clip(widths[..., :-1] / even, 0, 4), np.clip(widths[..., 1:] / even, 0, 4),
        np.clip(room[..., :-1], 0, 4), np.clip(room[..., 1:], 0, 4), np.clip(moved / most, -1, 1),
        np.full(gap.shape, np.sin(2 * np.pi * phase)), np.full(gap.shape, np.cos(2 * np.pi * phase)),
        np.full(gap.shape, float(grew)), np.clip(reactive / most, -1, 1),
    ]
    return np.stack(columns, axis=-1)
