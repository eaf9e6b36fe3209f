"""The simulation loop: forces on ranks, moves, growth, division, and rebalancing at a fixed cadence."""

from __future__ import annotations

import uuid
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import gru
from ..sources.scratch import scratch, settled
from . import grid, mechanics, score
from .interactions import slab_push
from .partitioner import bounds_of, enforce_min_width
from .ghosts import min_width
from .policies import Controller

LOG = "event int, iteration int, rank int, elements bigint, tests bigint, seconds double, first_slice int, last_slice int, moved int"


@dataclass(frozen=True)
class Plan:
    """What a run does; growth and division happen with every `growth` iterations (0: never)."""

    iterations: int
    cadence: int = 100
    ranks: int = 8
    slices: int = 256
    dt: float = 100.0
    policy: str = "reactive"
    growth: int = 0
    divide_at: int = 10


def simulate(elements: DataFrame, cutoff: float, plan: Plan, folder: str | None = None) -> tuple[DataFrame, DataFrame]:
    """The tissue after all iterations, and a log with one row for each rank and rebalancing event.

    Each iteration places sites and ghosts at their ranks and sweeps them, which gives the elements
    their steps; its rows are written to `folder`, a shared one, which cuts the lineage and lets a lost
    executor cost one iteration only. The slices keep their place on x, and elements beyond them
    belong to the first or last rank. The driver holds the bounds and P numbers for each event:
    work is told by the tests made, so runs repeat exactly; the seconds are logged beside them.
    """
    spark: SparkSession = elements.sparkSession
    folder = folder or scratch(spark, f"run-{uuid.uuid4().hex}")
    elements = settled(elements.select("cell_id", F.col("element_no").cast("bigint").alias("element_no"), *grid.AXES, "cell_type", "born"))
    scored = score.cell_work(elements, cutoff)
    low, high = score.extent(elements, cutoff)
    work = [r.work for r in score.slice_histogram(scored, low, high, plan.slices).orderBy("slice_id").collect()]  # plan.slices numbers
    thickness = (high - low) / plan.slices
    least = min_width(cutoff, thickness)
    ranks = max(1, min(plan.ranks, plan.slices // max(1, least)))
    bounds = np.array(enforce_min_width(bounds_of(work, ranks), least))
    control = Controller(plan.policy, bounds, plan.slices, least, gru.trained() if plan.policy == "learned" else None)
    floor = elements.agg(F.min("z")).first()[0]
    names = elements.columns
    current, log, spent = elements, [], np.zeros((3, ranks))
    for k in range(plan.iterations):
        cuts = [low + thickness * b for b in control.bounds[1:-1].tolist()]
        moved = mechanics.step(current, cutoff, plan.dt, lambda spots: slab_push(spots, cutoff, cuts), floor).select(*names, "tests", "rank", "seconds")  # noqa: B023
        path = f"{folder}/{k}"
        moved.write.parquet(path)
        rows = spark.read.schema(moved.schema).parquet(path)
        for r in rows.groupBy("rank").agg(F.count(F.lit(1)).alias("n"), F.sum("tests").alias("tests"), F.sum("seconds").alias("seconds")).collect():  # one for each rank
            spent[:, r["rank"]] += (r["n"], r["tests"], r["seconds"])
        current = rows.select(*names)
        grown = plan.growth and (k + 1) % plan.growth == 0
        if grown:
            current = mechanics.divide(mechanics.grow(current), plan.divide_at).select(*names)
        if (k + 1) % plan.cadence == 0 or k + 1 == plan.iterations:
            old = control.bounds
            phase = ((k + 1) % plan.growth) / plan.growth if plan.growth else 0.0
            new = control.act(spent[1], phase, float(bool(grown)))
            out = np.abs(new - old)
            log += [(len(log) // ranks, k + 1, r, int(spent[0, r]), int(spent[1, r]), float(spent[2, r]), int(old[r]), int(old[r + 1]) - 1, int(out[r + 1]) if r + 1 < ranks else 0) for r in range(ranks)]
            spent = np.zeros((3, ranks))
    return current, spark.createDataFrame(log, LOG)
