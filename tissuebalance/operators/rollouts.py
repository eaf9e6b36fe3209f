"""Rollouts of many scenarios and policies at once: one group each, sequential only in time."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import gru
from .policies import POLICIES, rollout
from .scenarios import REGIMES, Scenario, portable_jitter, scenario

ROLLOUT = "run_id string, policy string, ranks int, scenario_id bigint, step int, bounds array<int>, moved int, moved_work double, i_global double, t_max double, times array<double>"
COLUMNS = [part.split()[0] for part in ROLLOUT.split(", ")]


def labelled(log: list[dict], policy: str, ranks: int, scenario_id: int) -> pd.DataFrame:
    return pd.DataFrame(log).assign(run_id=f"{scenario_id}-{ranks}-{policy}", policy=policy, ranks=ranks, scenario_id=scenario_id)[COLUMNS]


def synthetic(spark: SparkSession, ids: list[int], ranks: list[int], steps: int = 100, policies: tuple[str, ...] = POLICIES, observed: str = "times", regime: str = "restless", per_rank: int | None = None, ground: DataFrame | None = None) -> DataFrame:
    """The rollout log of generated scenarios, on the ground (scenario_id, ground: counts along the axis) of each where given."""
    runs = spark.createDataFrame([(int(i), int(p), q) for i in ids for p in ranks for q in policies], "scenario_id bigint, ranks int, policy string")
    runs = runs.withColumn("ground", F.lit(None).cast("array<bigint>")) if ground is None else runs.join(F.broadcast(ground), "scenario_id")
    weights = gru.dumps(gru.trained())

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        r = rows.iloc[0]
        log = rollout(scenario(int(r.scenario_id), steps, int(r.ranks), per_rank, REGIMES[regime], r.ground), r.policy, gru.loads(weights), observed=observed)
        return labelled(log, r.policy, int(r.ranks), int(r.scenario_id))

    return runs.groupBy("scenario_id", "ranks", "policy").applyInPandas(run, ROLLOUT)


def replay(loads: DataFrame, m: int, ranks: list[int], policies: tuple[str, ...] = POLICIES, least: int = 2, noise: float = 0.02, seeds: int = 3, observed: str = "times", period: int = 10, steps: int = 100) -> DataFrame:
    """The rollout log of a recorded trace (step, slice_id, work), with seeded measurement noise.

    Slices are first put into one array for each step, of m numbers. A group holds the
    steps * m numbers of one trace. The growth phase has the given period, and an event counts as
    growth where the total load rose by more than a tenth.
    """
    runs = F.explode(F.array(*(F.struct(F.lit(p).alias("ranks"), F.lit(q).alias("policy"), F.lit(s).cast("bigint").alias("scenario_id")) for p in ranks for q in policies for s in range(seeds))))
    rows = loads.groupBy("step").agg(F.collect_list(F.struct("slice_id", "work")).alias("slices")).withColumn("run", runs).select("step", "slices", "run.*")
    weights = gru.dumps(gru.trained())

    def run(part: pd.DataFrame) -> pd.DataFrame:
        r = part.iloc[0]
        work = np.zeros((max(steps, int(part["step"].max()) + 1), m))
        for t, slices in zip(part["step"], part["slices"], strict=True):
            for one in slices:
                work[t, one["slice_id"]] = one["work"]
        p, n, total = int(r.ranks), len(work), work.sum(axis=1)
        jitter = np.array([[portable_jitter(noise, int(r.scenario_id), t, k) for k in range(p)] for t in range(n)])
        grew = np.concatenate([[0.0], (total[1:] > 1.1 * total[:-1]).astype(float)])
        trace = Scenario(p, m, least, work, jitter, (np.arange(n) % period) / period, grew)
        return labelled(rollout(trace, r.policy, gru.loads(weights), observed=observed), r.policy, p, int(r.scenario_id))

    return rows.groupBy("ranks", "policy", "scenario_id").applyInPandas(run, ROLLOUT)


def policy_table(log: DataFrame) -> DataFrame:
    """Mean imbalance, slices moved and runtime of each policy and rank count, averaged over runs."""
    runs = log.groupBy("policy", "ranks", "scenario_id").agg(F.avg("i_global").alias("i"), F.sum("moved").alias("m"), F.sum("moved_work").alias("w"), F.sum("t_max").alias("t"))
    return runs.groupBy("policy", "ranks").agg(
        F.count(F.lit(1)).alias("runs"), F.avg("i").alias("mean_imbalance"), F.min("i").alias("least_imbalance"), F.max("i").alias("most_imbalance"),
        F.avg("m").alias("moved"), F.avg("w").alias("moved_work"), F.avg("t").alias("runtime"),
    )
