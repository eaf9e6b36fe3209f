"""Balancing policies and their rollouts on load traces, with whole-slice boundaries."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from ..functions import balance, gru
from ..functions.balance import Rule
from .partitioner import bounds_of, enforce_min_width, optimal_bounds
from .scenarios import Scenario

POLICIES = ("static", "persistence", "holt", "reactive", "learned")
#: Not a policy that could run: it knows the next load and cuts it best.
BOUND = "clairvoyant"


def whole_units(load: np.ndarray) -> list[int]:
    """Loads in millionths of their sum."""
    total = load.sum() or 1.0
    return [int(v) for v in np.floor(load / total * 1e6 + 0.5)]


def cut(load: np.ndarray, ranks: int, least: int) -> np.ndarray:
    """A work-aware cut of loads as they are."""
    return np.array(enforce_min_width(bounds_of(whole_units(load), ranks), least))


def bound_of_step(m: int, ranks: int) -> float:
    return float(max(2, int(0.1 * m / ranks + 0.5)))


@dataclass
class Controller:
    """One policy at work: bounds in force and what it remembers. Times are those of the last interval."""

    policy: str
    bounds: np.ndarray
    slices: int
    least: int
    weights: gru.Weights | None = None
    rule: Rule = Rule()
    most: float = 0.0
    state: dict = field(default_factory=dict)

    def __post_init__(self) -> None:
        q = len(self.bounds) - 2
        self.most = self.most or bound_of_step(self.slices, q + 1)
        self.state = self.state or {"before": None, "moved": np.zeros(q), "carried": np.zeros(q), "hidden": np.zeros((q, gru.HIDDEN)), "level": None, "trend": None}

    def act(self, seen: np.ndarray, phase: float = 0.0, grew: float = 0.0, load: np.ndarray | None = None, coming: np.ndarray | None = None) -> np.ndarray:
        """The next bounds. load: the slices' own loads, where forecasts may see them; coming: the true next loads."""
        s, bounds, ranks = self.state, self.bounds, len(self.bounds) - 1
        widths, gap, new = np.diff(bounds), balance.local_imbalance(seen), bounds
        if self.policy in ("reactive", "learned", "untrained"):
            step = balance.proposal(seen, widths, self.rule)
            if self.policy == "reactive":
                step = np.clip(step, -self.most * (1 - self.rule.margin), self.most * (1 - self.rule.margin))
            else:
                before = gap if s["before"] is None else s["before"]
                x = balance.features(seen, widths, before, s["moved"], np.clip(step, -self.most, self.most), phase, grew, self.slices, ranks, self.least, self.most)
                s["hidden"], residual = gru.step(x, s["hidden"], self.weights if self.policy == "learned" else gru.init(0))
                step = balance.guard(balance.combine(step, residual, self.most, self.rule), gap, self.rule.mode)
            steps, s["carried"] = balance.whole(np.round(step, 9), self.rule.rounding, s["carried"])
            new = balance.sweep(bounds, steps, self.least)
        elif self.policy in ("persistence", "holt"):
            load = np.repeat(balance.ratio(seen, widths), widths) if load is None else load
            if self.policy == "holt":
                s["level"], s["trend"] = (load, np.zeros_like(load)) if s["level"] is None else balance.holt(s["level"], s["trend"], load)
                load = np.maximum(s["level"] + s["trend"], 0)
            new = cut(load, ranks, self.least)
        elif self.policy == BOUND and coming is not None:
            new = np.array(enforce_min_width(optimal_bounds(whole_units(coming), ranks), self.least))
        s["before"], s["moved"], self.bounds = gap, (new - bounds)[1:-1], new
        return new


def rollout(s: Scenario, policy: str, weights: gru.Weights | None = None, rule: Rule = Rule(), observed: str = "times", most: float = 0.0) -> list[dict]:
    """One row for each event: bounds in force, slices and work moved after it, imbalance of the true times.

    Forecasts see either rank times spread evenly over slices ('times') or the true histogram
    ('histogram'). Policies act on noisy times; measures use the true ones.
    """
    control = Controller(policy, cut(s.loads[0], s.ranks, s.least), s.slices, s.least, weights, rule, most)
    out = []
    for t, load in enumerate(s.loads):
        bounds = control.bounds
        times = balance.rank_times(load, bounds)
        coming = s.loads[min(t + 1, len(s.loads) - 1)]
        new = control.act(times * s.jitter[t], s.phase[t], s.grew[t], load if observed == "histogram" else None, coming)
        upto = np.concatenate([[0.0], np.cumsum(load)])
        out.append({
            "step": t, "bounds": bounds.tolist(), "moved": int(np.abs(new - bounds).sum()), "moved_work": float(np.abs(upto[new] - upto[bounds]).sum()),
            "i_global": float(balance.global_imbalance(times)), "t_max": float(times.max()), "times": times.tolist(),
        })
    return out


def summary(rows: list[dict]) -> dict:
    return {"mean_imbalance": float(np.mean([r["i_global"] for r in rows])), "moved": sum(r["moved"] for r in rows), "runtime": sum(r["t_max"] for r in rows)}
