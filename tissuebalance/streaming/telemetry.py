"""Rank times as a stream: windowed imbalance, and a controller that keeps its state per run."""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions import gru
from ..operators.policies import Controller

TELEMETRY = "run_id string, step int, rank int, ts timestamp, t_obs double"
MOVES = "run_id string, step int, boundary int, bound int, moved int, acted boolean"


def watermarked(telemetry: DataFrame, late: str) -> DataFrame:
    return telemetry.withWatermark("ts", late) if telemetry.isStreaming else telemetry


def windowed_imbalance(telemetry: DataFrame, ranks: int, late: str = "10 minutes", width: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Global imbalance of each run and window: each rank's times are added up first.

    Ranks are 0 .. ranks - 1; one that reports nothing in a window is left out of it. telemetry
    may be a stream or a table.
    """
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    held = watermarked(telemetry, late).groupBy("run_id", window.alias("w")).agg(F.count(F.lit(1)).alias("n"), *(F.sum(F.when(F.col("rank") == r, F.col("t_obs"))).alias(f"t{r}") for r in range(ranks)))
    times = F.array_compact(F.array(*(F.col(f"t{r}") for r in range(ranks))))
    mean = F.aggregate("times", F.lit(0.0), lambda s, t: s + t) / F.size("times")
    return held.withColumn("times", times).select("run_id", F.col("w.start").alias("start"), "n", F.try_divide(F.array_max("times") - F.array_min("times"), mean).alias("i_global"))


def sessions(telemetry: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """Stretches of a run's reports without a pause of that length."""
    held = watermarked(telemetry, late).groupBy("run_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n"), F.sum("t_obs").alias("t"))
    return held.select("run_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "t")


def reported_once(telemetry: DataFrame, late: str = "10 minutes") -> DataFrame:
    """Reports without those that repeat a run's step and rank."""
    keys = ["run_id", "step", "rank"]
    return watermarked(telemetry, late).dropDuplicatesWithinWatermark(keys) if telemetry.isStreaming else telemetry.dropDuplicates(keys)


def controlled(telemetry: DataFrame, ranks: int, m: int, least: int = 1, policy: str = "reactive", late: str = "10 minutes") -> DataFrame:
    """Boundary moves of each run: one row for each boundary and step that it acted on, in the order of steps.

    Bounds start uniform. The step that follows the last one is acted on as soon as all its ranks
    have reported. Any other waits until the watermark has passed its reports, so that nothing
    earlier can come any more; it is then acted on if it is complete. One that is not changes
    nothing and gives a single row with acted = false and boundary 0. Steps are expected to begin
    in time order; a rank's later report of one step replaces its earlier one. State holds the
    controller and the steps that wait, which the watermark bounds.
    """
    text = gru.dumps(gru.trained()) if policy == "learned" else None

    def run(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.exists:
            control, waiting, done = pickle.loads(state.get[0])
        else:
            control, waiting, done = Controller(policy, np.arange(ranks + 1) * m // ranks, m, least), {}, -1
        control.weights = gru.loads(text) if text else None
        if not state.hasTimedOut:
            for part in parts:
                for r in part.itertuples():
                    if r.step > done:
                        seen, last = waiting.setdefault(int(r.step), ({}, 0))
                        seen[int(r.rank)] = float(r.t_obs)
                        waiting[int(r.step)] = (seen, max(last, int(r.ts.timestamp() * 1000)))
        rows, passed = [], state.getCurrentWatermarkMs()
        for t in sorted(waiting):
            seen, last = waiting[t]
            if not (len(seen) == ranks and t == done + 1) and last >= passed:
                break
            del waiting[t]
            done = t
            if len(seen) < ranks:
                rows.append((key[0], t, 0, 0, 0, False))
                continue
            old = control.bounds
            new = control.act(np.array([seen[k] for k in range(ranks)]))
            rows += [(key[0], t, b, int(new[b]), int(new[b] - old[b]), True) for b in range(1, ranks)]
        control.weights = None
        state.update((pickle.dumps((control, waiting, done)),))
        if waiting:
            state.setTimeoutTimestamp(max(passed, min(last for _, last in waiting.values())) + 1)
        yield pd.DataFrame(rows, columns=["run_id", "step", "boundary", "bound", "moved", "acted"])

    return telemetry.withWatermark("ts", late).groupBy("run_id").applyInPandasWithState(run, MOVES, "state binary", "append", GroupStateTimeout.EventTimeTimeout)
