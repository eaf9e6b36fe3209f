"""Streams of telemetry: the stateful controller, windows, sessions and repeated reports."""

import numpy as np
import pytest
from tissuebalance.functions import balance
from tissuebalance.streaming.telemetry import TELEMETRY, controlled, reported_once, sessions, windowed_imbalance


def report(t, r):
    return 10.0 + r * (1 + t % 2) + t * (r == 1)


def telemetry(spark, rows):
    frame = spark.createDataFrame(rows, "run_id string, step int, rank int, ts string, t_obs double")
    return frame.selectExpr("run_id", "step", "rank", "cast(ts as timestamp) ts", "t_obs")


def streamed(spark, folder, batches, make, name):
    for k, rows in enumerate(batches):
        telemetry(spark, rows).coalesce(1).write.mode("append").parquet(f"{folder}/in")
        out = make(spark.readStream.schema(TELEMETRY).parquet(f"{folder}/in"))
        q = out.writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
        q.awaitTermination()
    return spark.read.parquet(f"{folder}/out").collect()


def expected(steps):
    bounds, out = np.array([0, 20, 40, 60]), {}
    for t in steps:
        step = np.clip(balance.proposal(np.array([report(t, r) for r in range(3)]), np.diff(bounds)), -2 * (1 - 1e-6), 2 * (1 - 1e-6))
        bounds = balance.sweep(bounds, balance.whole(np.round(step, 9))[0], 1)
        out |= {(t, b): int(bounds[b]) for b in (1, 2)}
    return out


def at(minute):
    return f"2024-01-01 {minute // 60:02d}:{minute % 60:02d}:00"


@pytest.mark.parametrize("shuffled", [False, True])
def test_controller_acts_in_order_and_goes_on_after_a_lost_report(spark, tmp_path, shuffled):
    rows = [("a", t, r, at(5 * t), report(t, r)) for t in range(12) for r in range(3) if (t, r) != (2, 1)]
    if shuffled:  # within what the watermark waits for
        rows = [rows[k] for k in np.argsort(np.arange(len(rows)) + np.random.default_rng(1).uniform(0, 5, len(rows)))]
    rows += [("a", 0, 0, at(55), 99.0), ("a", 30, 0, at(400), 1.0), ("a", 31, 0, at(600), 1.0)]
    batches = [rows[:7], rows[7:20], rows[20:], [("a", 32, 0, at(900), 1.0)]]
    got = streamed(spark, tmp_path, batches, lambda s: controlled(s, 3, 60, late="30 minutes"), "moves")
    want = expected([t for t in range(12) if t != 2])
    assert {(r.step, r.boundary): r.bound for r in got if r.acted} == want
    assert {r.step for r in got if not r.acted} >= {2, 30}
    assert [r.step for r in got if not r.acted].count(2) == 1


def test_imbalance_adds_up_each_rank_first(spark):
    rows = [("a", 0, 0, at(0), 4.0), ("a", 1, 0, at(1), 4.0), ("a", 0, 1, at(2), 6.0), ("b", 0, 0, at(3), 5.0)]
    got = {r.run_id: (r.n, r.i_global) for r in windowed_imbalance(telemetry(spark, rows), 2).collect()}
    assert got == {"a": (3, pytest.approx(2 / 7)), "b": (1, 0.0)}


def test_sessions_and_repeated_reports(spark, tmp_path):
    rows = [("a", 0, 0, at(0), 1.0), ("a", 0, 0, at(1), 1.0), ("a", 1, 0, at(50), 2.0)]
    assert sorted((r.n, r.t) for r in sessions(telemetry(spark, rows)).collect()) == [(1, 2.0), (2, 2.0)]
    got = streamed(spark, tmp_path, [rows], reported_once, "once")
    assert sorted((r.step, r["rank"]) for r in got) == [(0, 0), (1, 0)]
