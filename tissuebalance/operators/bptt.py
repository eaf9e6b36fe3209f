"""Gradient of the smooth balancing loop by hand: one pass forward through all events, one back."""

from __future__ import annotations

import numpy as np

from ..functions import balance, gru
from .policies import bound_of_step, cut

MARGIN = 1e-3
#: Beyond this many temperatures from a boundary a slice belongs to one side.
FAR = 24.0


class Loads:
    """Loads of one event for all episodes, with running sums."""

    def __init__(self, load: np.ndarray) -> None:
        self.load = load
        self.upto = np.concatenate([np.zeros((len(load), 1)), np.cumsum(load, axis=1)], axis=1)

    def left_of(self, bounds: np.ndarray, theta: float) -> tuple[np.ndarray, np.ndarray]:
        """The load left of each boundary, slices near it in part, and its slope."""
        m, reach = self.load.shape[1], int(np.ceil(FAR * theta)) + 1
        first = np.floor(bounds).astype(int) - reach
        at = first[..., None] + np.arange(2 * reach + 1)
        inside = (at >= 0) & (at < m)
        own = np.where(inside, np.take_along_axis(self.load[:, None, :], np.clip(at, 0, m - 1), axis=2), 0.0)
        s = 1 / (1 + np.exp(np.clip((at + 0.5 - bounds[..., None]) / theta, -60, 60)))
        part = s * own
        sure = np.take_along_axis(self.upto, np.clip(first, 0, m), axis=1)
        return sure + part.sum(axis=2), (part * (1 - s)).sum(axis=2) / theta


def gradient(w: gru.Weights, group: list, events: int, theta: float, c, rule: balance.Rule = balance.Rule()) -> tuple[float, gru.Weights]:
    """Loss and gradient of scenarios that share their numbers of ranks and slices."""
    n, ranks, m = len(group), group[0].ranks, group[0].slices
    least = np.array([[s.least] for s in group], float)
    start = np.stack([cut(s.loads[0], ranks, s.least) for s in group])
    noise, phase, grew = (np.stack([getattr(s, k)[:events] for s in group]) for k in ("jitter", "phase", "grew"))
    upto = np.stack([np.concatenate([np.zeros((events, 1)), np.cumsum(s.loads[:events], axis=1)], axis=1) for s in group])
    static = np.diff(np.take_along_axis(upto, np.broadcast_to(start[:, None, :], (n, events, ranks + 1)), axis=2), axis=2)
    scale = np.maximum(balance.relative_excess(static).mean(axis=1), 0.01)
    most, even, h_size = bound_of_step(m, ranks), m / ranks, gru.HIDDEN
    part = 1.0 / (scale * n * events)
    ends = start[:, :1].astype(float), start[:, -1:].astype(float)
    b, h = start[:, 1:-1].astype(float), np.zeros((n, ranks - 1, h_size))
    moved, before, wide = np.zeros_like(b), None, np.ones_like(b)
    rows, loss = np.arange(n), 0.0
    tape: list[tuple] = []
    for t in range(events):
        loads = Loads(np.stack([s.loads[t] for s in group]))
        left, slope = loads.left_of(b, theta)
        total = loads.upto[:, -1:]
        times = np.diff(np.concatenate([np.zeros((n, 1)), left, total], axis=1), axis=1)
        mean = total / ranks
        off = times / mean - 1
        spread = np.sqrt((off * off).sum(axis=1) / ranks + 1e-9)
        loss += (part * (off.max(axis=1) + c.spread * spread)).sum()
        seen = times * noise[:, t]
        lo, hi = seen[:, :-1], seen[:, 1:]
        gap = 2 * (hi - lo) / (hi + lo)
        widths = np.diff(np.concatenate([ends[0], b, ends[1]], axis=1), axis=1)
        slower = hi > lo
        slow_time, slow_width = np.where(slower, hi, lo), np.where(slower, widths[:, 1:], widths[:, :-1])
        gain = rule.alpha * (np.abs(gap) > rule.tau)
        ratio = gain * slow_width * (hi - lo) / (2 * slow_time) / most
        inside = np.clip(ratio, -1 + MARGIN, 1 - MARGIN)
        every = (seen.max(axis=1) - seen.min(axis=1)) / mean[:, 0]
        raw = np.stack([gap, gap - (gap if before is None else before), every[:, None] * wide, widths[:, :-1] / even, widths[:, 1:] / even, (widths[:, :-1] - least) / even, (widths[:, 1:] - least) / even, moved / most], axis=-1)
        low, high = np.array([-2, -2, 0, 0, 0, 0, 0, -1.0]), np.array([2, 2, 4, 4, 4, 4, 4, 1.0])
        live = (raw >= low) & (raw <= high)
        turn = 2 * np.pi * phase[:, t, None]
        x = np.concatenate([np.clip(raw, low, high), np.stack([np.sin(turn) * wide, np.cos(turn) * wide, grew[:, t, None] * wide, inside], axis=-1)], axis=-1)
        a, z = x @ w["w_x"] + w["b_x"], h @ w["w_h"] + w["b_h"]
        reset, update = gru.sigmoid(a[..., :h_size] + z[..., :h_size]), gru.sigmoid(a[..., h_size : 2 * h_size] + z[..., h_size : 2 * h_size])
        fresh = np.tanh(a[..., 2 * h_size :] + reset * z[..., 2 * h_size :])
        new_h = (1 - update) * fresh + update * h
        bent = np.tanh(np.arctanh(inside) + (new_h @ w["head"] + w["bias"])[..., 0])
        leak = np.where(bent * gap > 0, 1.0, 0.1)  # leaky here, hard when deployed
        free = bent * most * leak
        step = np.clip(free, -np.maximum(widths[:, :-1] - least, 0) / 2, np.maximum(widths[:, 1:] - least, 0) / 2)
        loss += np.abs(step).sum() * c.migration / n
        tape.append((slope, mean, off, spread, seen, noise[:, t], gap, slower, slow_time, slow_width, gain, ratio, inside, live, x, h, z, reset, update, fresh, new_h, bent, leak, step == free, step, before is not None))
        b, h, moved, before = b + step, new_h, step, gap
    grads = {k: np.zeros_like(v) for k, v in w.items()}
    g_b, g_moved, g_before, g_h = np.zeros_like(b), np.zeros_like(b), np.zeros_like(b), np.zeros_like(h)
    for slope, mean, off, spread, seen, jitter, gap, slower, slow_time, slow_width, gain, ratio, inside, live, x, h, z, reset, update, fresh, new_h, bent, leak, whole, step, has_before in reversed(tape):
        g_step = g_b + g_moved + np.sign(step) * c.migration / n
        g_bent = g_step * whole * leak * most * (1 - bent * bent)
        g_inside = g_bent / (1 - inside * inside)
        g_h = g_h + g_bent[..., None] * w["head"][:, 0]
        grads["head"] += np.tensordot(new_h, g_bent, axes=((0, 1), (0, 1)))[:, None]
        grads["bias"] += g_bent.sum()
        g_fresh = g_h * (1 - update) * (1 - fresh * fresh)
        g_update = g_h * (h - fresh) * update * (1 - update)
        g_reset = g_fresh * z[..., 2 * h_size :] * reset * (1 - reset)
        g_a = np.concatenate([g_reset, g_update, g_fresh], axis=-1)
        g_z = np.concatenate([g_reset, g_update, g_fresh * reset], axis=-1)
        grads["w_x"] += np.tensordot(x, g_a, axes=((0, 1), (0, 1)))
        grads["w_h"] += np.tensordot(h, g_z, axes=((0, 1), (0, 1)))
        grads["b_x"] += g_a.sum(axis=(0, 1))
        grads["b_h"] += g_z.sum(axis=(0, 1))
        g_x, g_h = g_a @ w["w_x"].T, g_h * update + g_z @ w["w_h"].T
        g_inside = (g_inside + g_x[..., 11]) * (np.abs(ratio) <= 1 - MARGIN) / most
        g_raw = g_x[..., :8] * live
        g_gap = g_raw[..., 0] + g_before + (g_raw[..., 1] if has_before else 0.0)
        g_before = -g_raw[..., 1] if has_before else np.zeros_like(gap)
        g_moved = g_raw[..., 7] / most
        lo, hi = seen[:, :-1], seen[:, 1:]
        k = g_inside * gain / (2 * slow_time)
        g_slow_width, g_apart, g_slow_time = k * (hi - lo), k * slow_width, -k * slow_width * (hi - lo) / slow_time
        square = (hi + lo) ** 2
        g_hi = g_apart + 4 * lo / square * g_gap + np.where(slower, g_slow_time, 0)
        g_lo = -g_apart - 4 * hi / square * g_gap + np.where(slower, 0, g_slow_time)
        g_seen = np.zeros_like(seen)
        g_seen[:, 1:] += g_hi
        g_seen[:, :-1] += g_lo
        g_every = g_raw[..., 2].sum(axis=1) / mean[:, 0]
        g_seen[rows, seen.argmax(axis=1)] += g_every
        g_seen[rows, seen.argmin(axis=1)] -= g_every
        g_times = g_seen * jitter + (c.spread * part / (ranks * spread))[:, None] * off / mean
        g_times[rows, off.argmax(axis=1)] += part / mean[:, 0]
        g_widths = np.zeros_like(seen)
        g_widths[:, :-1] += (g_raw[..., 3] + g_raw[..., 5]) / even + np.where(slower, 0, g_slow_width)
        g_widths[:, 1:] += (g_raw[..., 4] + g_raw[..., 6]) / even + np.where(slower, g_slow_width, 0)
        g_b = g_b + (g_times[:, :-1] - g_times[:, 1:]) * slope + g_widths[:, :-1] - g_widths[:, 1:]
    return float(loss), grads
