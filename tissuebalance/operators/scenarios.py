"""Synthetic load traces: moving bumps, periodic growth, bursts and measurement jitter."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

PRIME = 2147483647


def portable_hash(*values: int) -> int:
    """Whole numbers only, so any engine can repeat it."""
    h = 17
    for v in values:
        h = (h * 48271 + v + 11) % PRIME
    return h


def portable_hash_of(*values: Column | int) -> Column:
    h = F.lit(17).cast("bigint")
    for v in values:
        h = (h * 48271 + v + 11) % PRIME
    return h


def portable_jitter(noise: float, *values: int) -> float:
    """A factor around 1 whose spread is about `noise`, evenly distributed."""
    return 1.0 + (portable_hash(*values) % 2001 - 1000) * (noise * 0.0017)


@dataclass
class Scenario:
    ranks: int
    slices: int
    least: int
    loads: np.ndarray
    jitter: np.ndarray
    phase: np.ndarray
    grew: np.ndarray


@dataclass(frozen=True)
class Regime:
    """How much a scenario changes: drift of its bumps per event, growth per period, chance and size of bursts, height over the floor."""

    drift: float = 1.0
    growth: tuple[float, float] = (1.05, 1.3)
    burst: float = 0.05
    burst_size: tuple[float, float] = (1.5, 3.0)
    height: tuple[float, float] = (0.5, 2.0)


#: restless and calm are what the controller is trained on, half each. still, with slices as thin as
#: published, is the published evaluation's: a static cut of two ranks stays within half a percent.
REGIMES = {"restless": Regime(), "calm": Regime(0.02, (1.0, 1.03), 0.01, (1.02, 1.1), (0.2, 0.6)), "still": Regime(0.004, (1.0, 1.008), 0.0, (1.0, 1.0), (0.1, 0.3))}


def held_out(scenario_id: int) -> bool:
    return scenario_id % 5 == 0


def scenario(scenario_id: int, steps: int, ranks: int | None = None, per_rank: int | None = None, regime: Regime = Regime(), ground: np.ndarray | None = None) -> Scenario:
    """Everything follows from the id: shape of the tissue, its loads (steps x slices) and noise factors.

    ground: recorded counts along the axis, which give the floor its shape; else it is even.
    """
    rng = np.random.default_rng(portable_hash(2026, scenario_id))
    ranks = ranks or int(rng.integers(2, 17))
    m = ranks * (per_rank or int(rng.integers(16, 65)))
    least = int(rng.integers(1, 5))
    at = np.arange(m) + 0.5
    n = int(rng.integers(1, 4))
    centre, width, height = rng.uniform(0, m, n), rng.uniform(m / 20, m / 4, n), rng.uniform(*regime.height, n)
    drift = regime.drift * rng.normal(0, m / 400, n)
    period, floor = int(rng.integers(8, 21)), rng.uniform(0.5, 1.5)
    if ground is not None:
        counts = np.asarray(ground, float)[np.arange(m) * len(ground) // m] + 1  # places without a record keep some load
        floor = floor * counts / counts.mean()
    burst, left = None, 0
    loads, grew = np.empty((steps, m)), np.zeros(steps)
    for t in range(steps):
        drift = 0.95 * drift + regime.drift * rng.normal(0, m / 1500, n)
        centre = np.clip(centre + drift, 0, m)
        if t and t % period == 0:
            height[rng.integers(n)] *= rng.uniform(*regime.growth)
            grew[t] = 1
        load = floor + (height * np.exp(-(((at[:, None] - centre) / width) ** 2) / 2)).sum(axis=1)
        if left == 0 and rng.random() < regime.burst:
            a = int(rng.integers(0, m))
            burst, left = (a, a + max(1, m // 10), rng.uniform(*regime.burst_size)), int(rng.integers(2, 7))
        if left:
            load[burst[0] : burst[1]] *= burst[2]
            left -= 1
        loads[t] = load
    noise = 1 + rng.uniform(0.01, 0.05) * rng.standard_normal((steps, ranks))
    return Scenario(ranks, m, least, loads, noise, (np.arange(steps) % period) / period, grew)


def portable_loads(spark: SparkSession, ids: int, steps: int, m: int, period: int = 12, ground: DataFrame | None = None) -> DataFrame:
    """scenario_id, step, slice_id, work of ids scenarios in whole numbers that any engine can repeat.

    Two triangular bumps per scenario move by whole slices, one of them grows with every period,
    and one event in twenty doubles a tenth of the slices. Rows are made on the cluster. ground: the
    load of each slice (scenario_id, slice_id, n) under the bumps, 0 where it has none; else 100.
    """
    keys = spark.range(ids * steps * m).select(F.expr(f"id div {steps * m}").alias("scenario_id"), F.expr(f"id div {m} % {steps}").alias("step"), (F.col("id") % m).alias("slice_id"))
    for k in (1, 2):
        own = [portable_hash_of(2026, F.col("scenario_id"), 10 * k + i) for i in range(4)]
        keys = keys.withColumns({"_start": own[0] % m, "_speed": own[1] % 5, "_width": own[2] % (m // 5) + m // 20, "_height": own[3] % 150 + 50})
        apart = f"abs(slice_id - (_start + _speed * step * {m} div 400) % {m})"
        grown = f" + 20 * (step div {period})" if k == 1 else ""
        keys = keys.withColumn(f"_bump{k}", F.expr(f"greatest(0, (_height{grown}) * (_width - {apart})) div _width"))
    hit = portable_hash_of(2027, F.col("scenario_id"), F.col("step"))
    burst = (hit % 20 == 0) & (F.expr(f"slice_id * 10 div {m}") == hit % 10)
    keys = keys.withColumn("n", F.lit(100)) if ground is None else keys.join(F.broadcast(ground), ["scenario_id", "slice_id"], "left")
    work = F.when(burst, 2).otherwise(1) * (F.col("_bump1") + F.col("_bump2") + F.coalesce("n", F.lit(0)))
    return keys.select("scenario_id", F.col("step").cast("int").alias("step"), F.col("slice_id").cast("int").alias("slice_id"), work.cast("bigint").alias("work"))


def portable_rows(scenario_id: int, steps: int, m: int, period: int = 12):
    """The same rows of one scenario, in plain whole numbers."""
    own = {k: [portable_hash(2026, scenario_id, 10 * k + i) for i in range(4)] for k in (1, 2)}
    for t in range(steps):
        hit = portable_hash(2027, scenario_id, t)
        for z in range(m):
            work = 100
            for k, (start, speed, wide, high) in own.items():
                width, height = wide % (m // 5) + m // 20, high % 150 + 50 + (20 * (t // period) if k == 1 else 0)
                work += max(0, height * (width - abs(z - (start % m + speed % 5 * t * m // 400) % m))) // width
            yield scenario_id, t, z, 2 * work if hit % 20 == 0 and z * 10 // m == hit % 10 else work
