"""Offline training of the boundary controller in a smooth simulated loop."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from . import bptt
from ..functions import balance, gru
from ..functions.tape import Var, concat, of, stack
from .policies import bound_of_step, cut, rollout, summary
from .scenarios import REGIMES, held_out, portable_hash, scenario


@dataclass(frozen=True)
class Config:
    """The published budget, rate, decay, clip, batch, loss weights and temperatures. calm: our share of calm scenarios."""

    steps: int = 6000
    events: int = 50
    batch: int = 32
    rate: float = 3e-3
    final: float = 0.05
    clip: float = 1.0
    spread: float = 0.3
    migration: float = 5e-4
    hot: float = 1.5
    cold: float = 0.4
    seed: int = 1
    calm: float = 0.5


def soft_times(bounds: Var, loads: np.ndarray, theta: float) -> Var:
    """Rank times where a slice belongs to ranks by a difference of two sigmoids."""
    at = np.arange(loads.shape[-1]) + 0.5
    s = 1 / (1 + np.exp(np.clip((at - bounds.value[..., None]) / theta, -60, 60)))
    left = Var((s * loads[:, None, :]).sum(axis=-1), ((bounds, lambda g: g * (s * (1 - s) * loads[:, None, :]).sum(axis=-1) / theta),))
    total = loads.sum(axis=-1, keepdims=True)
    return concat([left, of(total)]) - concat([of(np.zeros_like(total)), left])


def gru_step(x: Var, h: Var, w: dict[str, Var]) -> tuple[Var, Var]:
    n = gru.HIDDEN
    a, b = x @ w["w_x"] + w["b_x"], h @ w["w_h"] + w["b_h"]
    reset, update = (a[..., :n] + b[..., :n]).sigmoid(), (a[..., n : 2 * n] + b[..., n : 2 * n]).sigmoid()
    fresh = (a[..., 2 * n :] + reset * b[..., 2 * n :]).tanh()
    h = (of(1.0) - update) * fresh + update * h
    return h, (h @ w["head"] + w["bias"])[..., 0]


def rollout_loss(w: dict[str, Var], group: list, events: int, theta: float, c: Config, rule: balance.Rule = balance.Rule()) -> Var:
    """The mean loss of scenarios that share their numbers of ranks and slices, on the tape: what bptt.gradient is held against."""
    ranks, m = group[0].ranks, group[0].slices
    least = np.array([[s.least] for s in group], float)
    loads = np.stack([s.loads[:events] for s in group])
    noise = np.stack([s.jitter[:events] for s in group])
    start = np.stack([cut(s.loads[0], ranks, s.least) for s in group]).astype(float)
    static = np.stack([[balance.relative_excess(balance.rank_times(s.loads[t], cut(s.loads[0], ranks, s.least))) for t in range(events)] for s in group]).mean(axis=1)
    scale = np.maximum(static, 0.01)
    most, even = bound_of_step(m, ranks), m / ranks
    bounds = of(start[:, 1:-1])
    ends = of(start[:, :1]), of(start[:, -1:])
    hidden, moved, before = of(np.zeros((len(group), ranks - 1, gru.HIDDEN))), of(np.zeros_like(start[:, 1:-1])), None
    loss = of(0.0)
    for t in range(events):
        times = soft_times(bounds, loads[:, t], theta)
        mean = of(loads[:, t].sum(axis=-1, keepdims=True) / ranks)
        excess = times.max(-1) / mean[:, 0] - 1.0
        off = times / mean - 1.0
        spread = ((off * off).sum(axis=-1) / float(ranks) + 1e-9).sqrt()
        loss = loss + ((excess + spread * c.spread) / scale).sum() / float(len(group) * events)
        seen = times * noise[:, t]
        left, right = seen[:, :-1], seen[:, 1:]
        gap = (right - left) / ((right + left) * 0.5)
        whole = concat([ends[0], bounds, ends[1]])
        widths = whole[:, 1:] - whole[:, :-1]
        slower = right.value > left.value
        slow_time = right * slower + left * ~slower
        slow_width = widths[:, 1:] * slower + widths[:, :-1] * ~slower
        fires = np.abs(gap.value) > rule.tau
        reactive = slow_width * (right - left) / (slow_time * 2.0) * (rule.alpha * fires)
        inside = (reactive / most).clip(-1 + 1e-3, 1 - 1e-3)
        all_gap = (seen.max(-1) + (-seen).max(-1)) / mean[:, 0]
        wide = np.ones_like(gap.value)
        phase = np.array([s.phase[t] for s in group])[:, None]
        x = stack([
            gap.clip(-2, 2), (gap - (before if before is not None else gap)).clip(-2, 2), (all_gap[:, None] * wide).clip(0, 4),
            (widths[:, :-1] / even).clip(0, 4), (widths[:, 1:] / even).clip(0, 4), ((widths[:, :-1] - least) / even).clip(0, 4), ((widths[:, 1:] - least) / even).clip(0, 4),
            (moved / most).clip(-1, 1), of(np.sin(2 * np.pi * phase) * wide), of(np.cos(2 * np.pi * phase) * wide), of(np.array([[s.grew[t]] for s in group]) * wide), inside,
        ])
        hidden, residual = gru_step(x, hidden, w)
        step = (inside.atanh() + residual).tanh() * most
        step = step * np.where(step.value * gap.value > 0, 1.0, 0.1)  # leaky here, hard when deployed
        room_right, room_left = widths.value[:, 1:] - least, widths.value[:, :-1] - least
        step = step.clip(-np.maximum(room_left, 0) / 2, np.maximum(room_right, 0) / 2)
        loss = loss + step.abs().sum() * (c.migration / len(group))
        bounds, moved, before = bounds + step, step, gap
    return loss


def gradient(w: gru.Weights, ids: list[int], ranks: int, per_rank: int, theta: float, c: Config) -> tuple[float, gru.Weights]:
    """Loss and gradient of some episodes of one shape."""
    regimes = ["calm" if portable_hash(i) % 1000 < 1000 * c.calm else "restless" for i in ids]
    return bptt.gradient(w, [scenario(i, c.events, ranks, per_rank, REGIMES[r]) for i, r in zip(ids, regimes, strict=True)], c.events, theta, c)


def over_spark(spark: SparkSession, parts: int) -> Callable:
    """The same gradient with the episodes of a batch dealt over tasks; the driver averages `parts` rows."""

    def run(w: gru.Weights, ids: list[int], ranks: int, per_rank: int, theta: float, c: Config) -> tuple[float, gru.Weights]:
        names, text = sorted(w), gru.dumps(w, 17)

        def share(it: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for rows in it:
                if len(rows):
                    loss, g = gradient(gru.loads(text), rows["id"].tolist(), ranks, per_rank, theta, c)
                    yield pd.DataFrame({"n": [len(rows)], "loss": [loss], "g": [np.concatenate([g[n].ravel() for n in names])]})

        rows = spark.createDataFrame([(i,) for i in ids], "id bigint").repartition(parts).mapInPandas(share, "n bigint, loss double, g array<double>").collect()
        total, flat = sum(r.n for r in rows), sum(r.n * np.array(r.g) for r in rows) / sum(r.n for r in rows)
        cuts = np.split(flat, np.cumsum([w[n].size for n in names])[:-1])
        return sum(r.n * r.loss for r in rows) / total, {n: x.reshape(w[n].shape) for n, x in zip(names, cuts, strict=True)}

    return run


def train(c: Config = Config(), log: Callable | None = None, how: Callable = gradient) -> gru.Weights:
    """Adam with a cosine rate on batches of scenarios that evaluation never sees; the episodes of a batch share their shape."""
    w = gru.init(c.seed)
    first, second = ({k: np.zeros_like(v) for k, v in w.items()} for _ in range(2))
    rng = np.random.default_rng(c.seed)
    for k in range(c.steps):
        ranks, per_rank = int(rng.integers(2, 17)), int(rng.integers(16, 65))
        ids = [i for i in rng.integers(1, 1 << 30, 2 * c.batch).tolist() if not held_out(i)][: c.batch]
        theta = c.hot * (c.cold / c.hot) ** (k / max(1, c.steps - 1))
        loss, grads = how(w, ids, ranks, per_rank, theta, c)
        norm = np.sqrt(sum((g * g).sum() for g in grads.values()))
        rate = c.rate * (c.final + (1 - c.final) * (1 + np.cos(np.pi * k / c.steps)) / 2)
        for n, g in grads.items():
            g = g * min(1.0, c.clip / max(norm, 1e-12))
            first[n], second[n] = 0.9 * first[n] + 0.1 * g, 0.999 * second[n] + 0.001 * g * g
            w[n] = w[n] - rate * first[n] / (1 - 0.9 ** (k + 1)) / (np.sqrt(second[n] / (1 - 0.999 ** (k + 1))) + 1e-8)
        if log and k % 10 == 0:
            log(f"{k} {loss:.4f}")
    return w


def sweep(spark: SparkSession, grid: list[Config], probes: list[int], ranks: int = 8) -> DataFrame:
    """One training for each setting, all at once; steps, rate, migration, seed, and what held-out probes say of the weights."""
    rows = [(k, *(float(getattr(c, n)) for n in ("steps", "events", "batch", "rate", "migration", "seed"))) for k, c in enumerate(grid)]
    todo = spark.createDataFrame(rows, "k int, steps double, events double, batch double, rate double, migration double, seed double").repartition(len(rows), "k")

    def run(part: pd.DataFrame) -> pd.DataFrame:
        r = part.iloc[0]
        w = train(Config(int(r.steps), int(r.events), int(r.batch), rate=r.rate, migration=r.migration, seed=int(r.seed)))
        out = [summary(rollout(scenario(i, 100, ranks), "learned", w)) for i in probes]
        return part.assign(mean_imbalance=float(np.mean([o["mean_imbalance"] for o in out])), moved=float(np.mean([o["moved"] for o in out])), weights=gru.dumps(w))

    return todo.groupBy("k").applyInPandas(run, "k int, steps double, events double, batch double, rate double, migration double, seed double, mean_imbalance double, moved double, weights string")
