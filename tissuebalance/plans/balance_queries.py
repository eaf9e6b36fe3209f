"""Queries on load traces: rank times, imbalance, the reactive rule, forecasts and rollouts."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import balance, gru
from ..operators import measures, partitioner, rollouts
from ..operators.policies import BOUND, POLICIES, bound_of_step, rollout, summary
from ..operators.scenarios import PRIME, portable_loads, scenario
from ..sources.tissues import event_cloud, order_tissue, table
from . import loop_sql, sql
from .tissue_queries import histogram

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
M, RANKS, STEPS, VELOCITY, SPAN = 256, 8, 100, 20, 12_000_000
WINDOW_US = 30 * 86_400_000_000 // STEPS
BOUNDS = [0, 10, 22, 34, 48, 64, 86, 120, M]


def add(name: str, query, oracle: str | None = None) -> None:
    QUERIES[name] = query
    if oracle:
        ORACLES[name] = oracle


def load_trace(spark: SparkSession, folder: str, steps: int = STEPS, velocity: int = VELOCITY) -> DataFrame:
    """step, slice_id, work: events accumulate over equal windows and drift right with their age.

    Equal events (window, speed and place, of which there is a fixed number) are counted before
    they are repeated for the windows that they live through.
    """
    width = 30 * 86_400_000_000 // steps
    events = event_cloud(spark, folder).groupBy("x", "k", F.expr(f"micros div {width}").alias("born")).agg(F.count(F.lit(1)).alias("n"))
    alive = events.select("x", "k", "born", "n", F.explode(F.sequence("born", F.lit(steps - 1).cast("bigint"))).alias("step"))
    at = F.expr(f"least({M - 1}, (x + {velocity} * k * (step - born) * 100 div {steps}) * {M} div {SPAN})")
    return alive.groupBy(F.col("step").cast("int").alias("step"), at.cast("int").alias("slice_id")).agg(F.sum("n").cast("bigint").alias("work"))


def order_trace(spark: SparkSession, folder: str) -> DataFrame:
    """step, slice_id, work of the growing order tissue: elements live from their birth on, through windows of 27 days, what comes later in the last."""
    born = F.expr(f"least({STEPS - 1}, datediff(born, date'1992-01-01') div 27)").cast("int")
    place = F.expr(f"least({M - 1}, greatest(0, (x + 1200000) * {M} div 2600000))").cast("int")
    counted = order_tissue(spark, folder).groupBy(born.alias("born"), place.alias("slice_id")).agg(F.count(F.lit(1)).alias("n"))
    return counted.select("slice_id", "n", F.explode(F.sequence("born", F.lit(STEPS - 1))).alias("step")).groupBy("step", "slice_id").agg(F.sum("n").cast("bigint").alias("work"))


_TRACE = f"""WITH {sql.elements('event')}, alive AS (SELECT x, k, micros // {WINDOW_US} AS born FROM e),
steps AS (SELECT a.*, s.i AS step FROM alive a JOIN range({STEPS}) s(i) ON s.i >= a.born),
tr AS (SELECT step::INTEGER AS step, least({M - 1}, (x + {VELOCITY} * k * (step - born) * 100 // {STEPS}) * {M} // {SPAN})::INTEGER AS slice_id, count(*)::BIGINT AS work FROM steps GROUP BY ALL)"""
_RANK = " + ".join(f"CASE WHEN slice_id >= {b} THEN 1 ELSE 0 END" for b in BOUNDS[1:-1])
_TIMES = f"""{_TRACE}, t0 AS (SELECT step, ({_RANK})::INTEGER AS rank, sum(work)::BIGINT AS t FROM tr GROUP BY ALL),
t AS (SELECT s.i::INTEGER AS step, r.i::INTEGER AS rank, coalesce(t0.t, 0)::BIGINT AS t FROM (SELECT DISTINCT step AS i FROM tr) s, range({RANKS}) r(i) LEFT JOIN t0 ON t0.step = s.i AND t0.rank = r.i)"""


def static_times(spark: SparkSession, folder: str) -> DataFrame:
    return measures.rank_curves(load_trace(spark, folder), BOUNDS)


add("load_trace_event", load_trace, f"{_TRACE} SELECT step, slice_id, work FROM tr")
add("rank_times_static", static_times, f"{_TIMES} SELECT step, rank, t FROM t")
add(
    "imbalance_static",
    lambda s, d: measures.global_imbalance(static_times(s, d)).withColumn("i_global", F.round("i_global", 6)),
    f"{_TIMES} SELECT step, round((max(t) - min(t))::DOUBLE / nullif(avg(t), 0), 6) AS i_global, max(t)::BIGINT AS t_max FROM t GROUP BY step",
)
add(
    "imbalance_mean_static",
    lambda s, d: measures.global_imbalance(static_times(s, d)).agg(F.round(F.avg("i_global"), 6).alias("mean_imbalance"), F.sum("t_max").alias("runtime")),
    f"{_TIMES}, i AS (SELECT (max(t) - min(t))::DOUBLE / nullif(avg(t), 0) AS g, max(t) AS m FROM t GROUP BY step) SELECT round(avg(g), 6) AS mean_imbalance, sum(m)::BIGINT AS runtime FROM i",
)
_WIDTHS = "[" + ", ".join(f"{b - a}.0::DOUBLE" for a, b in zip(BOUNDS, BOUNDS[1:], strict=False)) + "]"
_PAIRS = f"""{_TIMES}, n AS (SELECT step, rank + 1 AS boundary, t AS t_left, lead(t) OVER (PARTITION BY step ORDER BY rank) AS t_right FROM t),
l AS (SELECT *, (t_right - t_left)::DOUBLE / nullif((t_right + t_left) / 2.0, 0) AS i_local FROM n WHERE t_right IS NOT NULL)"""
add("imbalance_local_static", lambda s, d: measures.local_imbalance(static_times(s, d)).withColumn("i_local", F.round("i_local", 6)), f"{_PAIRS} SELECT step, boundary, t_left, t_right, round(i_local, 6) AS i_local FROM l")
add(
    "reactive_proposals",
    lambda s, d: measures.reactive_proposals(static_times(s, d), BOUNDS).select("step", "boundary", F.round("proposal", 6).alias("proposal")),
    f"{_PAIRS} SELECT step, boundary, round(CASE WHEN abs(i_local) > 0.02 THEN sign(i_local) * 0.5 * CASE WHEN t_right > t_left THEN ({_WIDTHS})[boundary + 1] ELSE ({_WIDTHS})[boundary] END * abs(t_right - t_left) / (2.0 * greatest(t_left, t_right)) ELSE 0 END, 6) AS proposal FROM l",
)
add(
    "persistence_forecast",
    lambda s, d: load_trace(s, d).select((F.col("step") + 1).alias("step"), "slice_id", F.col("work").alias("forecast")),
    f"{_TRACE} SELECT step + 1 AS step, slice_id, work AS forecast FROM tr",
)


def holt_forecast(spark: SparkSession, folder: str, a: float = 0.5, b: float = 0.25) -> DataFrame:
    """One step ahead for each slice with any load: level and trend folded over time in one expression."""
    dense = F.transform(F.sequence(F.lit(0), F.lit(STEPS - 1)), lambda t: F.coalesce(F.element_at("by_step", t), F.lit(0)).cast("double"))
    slices = load_trace(spark, folder).groupBy("slice_id").agg(F.map_from_entries(F.collect_list(F.struct("step", "work"))).alias("by_step"))
    fold = f"""aggregate(slice(loads, 2, {STEPS - 1}), struct(loads[0] as l, 0D as t), (s, x) -> struct({a}D * x + {1 - a}D * (s.l + s.t) as l,
      {b}D * ({a}D * x + {1 - a}D * (s.l + s.t) - s.l) + {1 - b}D * s.t as t), s -> greatest(s.l + s.t, 0D))"""
    return slices.withColumn("loads", dense).select("slice_id", F.round(F.expr(fold), 6).alias("forecast"))


add(
    "holt_forecast",
    holt_forecast,
    _TRACE.replace("WITH ", "WITH RECURSIVE ", 1) + f""", own AS (SELECT DISTINCT slice_id FROM tr), d AS (SELECT o.slice_id, s.i AS step, coalesce(work, 0)::DOUBLE AS x FROM own o CROSS JOIN range({STEPS}) s(i) LEFT JOIN tr ON tr.slice_id = o.slice_id AND tr.step = s.i),
h(slice_id, step, l, t) AS (SELECT slice_id, step, x, 0::DOUBLE FROM d WHERE step = 0 UNION ALL
  SELECT d.slice_id, d.step, 0.5::DOUBLE * x + 0.5::DOUBLE * (l + t), 0.25::DOUBLE * (0.5::DOUBLE * x + 0.5::DOUBLE * (l + t) - l) + 0.75::DOUBLE * t FROM h JOIN d ON d.slice_id = h.slice_id AND d.step = h.step + 1)
SELECT slice_id, round(greatest(l + t, 0), 6) AS forecast FROM h WHERE step = {STEPS - 1}""",
)


add(
    "load_trace_order",
    order_trace,
    f"""WITH {sql.elements('order')}, b AS (SELECT least({STEPS - 1}, date_diff('day', DATE '1992-01-01', born) // 27)::INTEGER AS born, least({M - 1}, greatest(0, (x + 1200000) * {M} // 2600000))::INTEGER AS slice_id, count(*) AS n FROM e GROUP BY ALL)
SELECT i::INTEGER AS step, slice_id, sum(n)::BIGINT AS work FROM b JOIN range({STEPS}) s(i) ON i >= born GROUP BY ALL""",
)
add(
    "imbalance_spread_static",
    lambda s, d: measures.spread(static_times(s, d)).select("step", F.round("excess", 6).alias("excess"), F.round("spread", 6).alias("spread")),
    f"{_TIMES} SELECT step, round((max(t) - avg(t)) / nullif(avg(t), 0), 6) AS excess, round(stddev_pop(t) / nullif(avg(t), 0), 6) AS spread FROM t GROUP BY step",
)

LEAST, NOISE = 2, 0.02


def event_log(spark: SparkSession, folder: str, policies: tuple[str, ...], steps: int = STEPS, ranks: tuple[int, ...] = (RANKS,), seeds: int = 1, **more) -> DataFrame:
    return rollouts.replay(load_trace(spark, folder, steps), M, list(ranks), policies, LEAST, NOISE, seeds, steps=steps, **more)


def shown(log: DataFrame) -> DataFrame:
    return log.select("step", F.array_join("bounds", ",").alias("bounds"), F.col("moved").cast("bigint").alias("moved"), F.round("i_global", 6).alias("i_global"), F.col("t_max").cast("bigint").alias("t_max"))


def rolled(policy: str, **more):
    return lambda s, d: shown(event_log(s, d, (policy,), **more))


_SHAPE = (RANKS, M, LEAST)
_PRE = loop_sql.lists(_TRACE.replace("WITH ", "WITH RECURSIVE ", 1), M, STEPS, RANKS, NOISE)
_LOOPS = {
    "static": loop_sql.static(*_SHAPE), "reactive": loop_sql.reactive(*_SHAPE, bound_of_step(M, RANKS)),
    "persistence": loop_sql.persistence(*_SHAPE), "holt": loop_sql.holt(*_SHAPE),
    "persistence_histogram": loop_sql.persistence(*_SHAPE, True), "holt_histogram": loop_sql.holt(*_SHAPE, True),
}


def looped(policy: str, select: str) -> str:
    return f"{_PRE}, {_LOOPS[policy]}, {loop_sql.log(RANKS)} {select}"


for _policy in POLICIES:
    add(f"rollout_{_policy}", rolled(_policy), looped(_policy, loop_sql.shown(RANKS)) if _policy in _LOOPS else None)
for _policy in ("persistence", "holt"):
    add(f"rollout_{_policy}_histogram", rolled(_policy, observed="histogram"), looped(f"{_policy}_histogram", loop_sql.shown(RANKS)))
add("rollout_clairvoyant", rolled(BOUND))
add("rollout_400_events", lambda s, d: event_log(s, d, ("reactive", "learned"), 400).select("policy", "step", F.array_join("bounds", ",").alias("bounds"), "moved", F.round("i_global", 6).alias("i_global")))
#: A controller with a head of zeros takes the steps of the clipped reactive rule, event by event.
add("rollout_untrained_equals_reactive", rolled("untrained"), looped("reactive", loop_sql.shown(RANKS)))

_MOVED = f"list_sum(list_transform(range(1, {RANKS + 2}), lambda i: abs(nb[i] - b[i])))"
_MOVED_WORK = f"list_sum(list_transform(range(1, {RANKS + 2}), lambda i: abs(c[nb[i] + 1] - c[b[i] + 1])))"
add(
    "migration_reactive",
    lambda s, d: measures.migration(event_log(s, d, ("reactive",))).select("run_id", "moved", F.col("moved_work").cast("bigint").alias("moved_work")),
    looped("reactive", f"SELECT '0-{RANKS}-reactive' AS run_id, sum({_MOVED})::BIGINT AS moved, sum({_MOVED_WORK})::BIGINT AS moved_work FROM log"),
)
add(
    "moved_slices_reactive",
    lambda s, d: measures.moved_slices(event_log(s, d, ("reactive",))).select("step", F.col("slice_id").cast("int").alias("slice_id"), "from_rank", "to_rank"),
    looped("reactive", f"""SELECT step, slice_id, from_rank, to_rank FROM (SELECT step, z::INTEGER AS slice_id, (len(list_filter(b, lambda e: e <= z)) - 1)::INTEGER AS from_rank, (len(list_filter(nb, lambda e: e <= z)) - 1)::INTEGER AS to_rank
  FROM log, range({M}) q(z) WHERE step < {STEPS - 1}) WHERE from_rank <> to_rank"""),
)
for _policy in ("static", "reactive", "holt"):
    add(
        f"rank_curves_{_policy}",
        lambda s, d, p=_policy: measures.rank_times(event_log(s, d, (p,))).select("step", "rank", F.col("t").cast("bigint").alias("t")),
        looped(_policy, f"SELECT step, (i - 1)::INTEGER AS rank, t[i]::BIGINT AS t FROM log, range(1, {RANKS + 1}) q(i)"),
    )
add("rank_curves_learned", lambda s, d: measures.rank_times(event_log(s, d, ("learned",))).select("step", "rank", F.col("t").cast("bigint").alias("t")))

FOUR = ("static", "persistence", "holt", "reactive")


def four_runs(spark: SparkSession, folder: str) -> DataFrame:
    """Imbalance, moves and runtime of the policies without weights, whose loops SQL can repeat."""
    log = event_log(spark, folder, FOUR)
    return log.groupBy("policy", "ranks").agg(F.avg("i_global").alias("mean_imbalance"), F.sum("moved").cast("bigint").alias("moved"), F.sum("t_max").alias("runtime"))


_FOUR = "WITH g AS (" + " UNION ALL ".join(f"(SELECT '{p}' AS policy, avg(i) AS mean_imbalance, sum(moved)::BIGINT AS moved, sum(t_max)::DOUBLE AS runtime FROM ({looped(p, f'SELECT (list_max(t) - list_min(t)) / list_avg(t) AS i, {_MOVED} AS moved, list_max(t) AS t_max FROM log')}))" for p in FOUR) + ")"
add(
    "savings_event",
    lambda s, d: measures.end_to_end(four_runs(s, d)).select("policy", "moved", F.round("mean_imbalance", 6).alias("mean_imbalance"), F.round("runtime_saved", 6).alias("runtime_saved"), F.round("mean_imbalance_saved", 6).alias("mean_imbalance_saved"), F.round("moved_ratio", 6).alias("moved_ratio"), F.round("moves_per_point", 4).alias("moves_per_point")),
    f"""{_FOUR}, s AS (SELECT mean_imbalance AS si, runtime AS sr, (SELECT moved FROM g WHERE policy = 'reactive') AS rm FROM g WHERE policy = 'static')
SELECT policy, moved, round(mean_imbalance, 6) AS mean_imbalance, round((sr - runtime) / sr, 6) AS runtime_saved, round((si - mean_imbalance) / si, 6) AS mean_imbalance_saved,
  round(rm::DOUBLE / nullif(moved, 0), 6) AS moved_ratio, round(CASE WHEN si > mean_imbalance THEN moved / ((si - mean_imbalance) * 100) END, 4) AS moves_per_point FROM g, s""",
)
add(
    "tradeoff_event",
    lambda s, d: measures.tradeoff(four_runs(s, d)).select("policy", "moved", F.round("mean_imbalance", 6).alias("mean_imbalance"), "pareto"),
    f"{_FOUR} SELECT policy, moved, round(mean_imbalance, 6) AS mean_imbalance, NOT EXISTS (SELECT 1 FROM g o WHERE o.mean_imbalance <= g.mean_imbalance AND o.moved <= g.moved AND (o.mean_imbalance < g.mean_imbalance OR o.moved < g.moved)) AS pareto FROM g",
)

EVERY = (*POLICIES, BOUND)
add("policy_table_event", lambda s, d: rollouts.policy_table(event_log(s, d, EVERY, ranks=(2, 4, 8, 16), seeds=3)))
add("end_to_end_event", lambda s, d: measures.end_to_end(rollouts.policy_table(event_log(s, d, EVERY, seeds=3))))
add("end_to_end_order", lambda s, d: measures.end_to_end(rollouts.policy_table(rollouts.replay(order_trace(s, d), M, [RANKS], EVERY, LEAST, NOISE))))
#: W11: every policy on the front that sweeps over the axis.
add("policy_table_front", lambda s, d: rollouts.policy_table(rollouts.replay(moving_front(s, d), 128, [4, 8], EVERY, LEAST, NOISE, steps=92)))


PLACES = 16


def recorded_ground(spark: SparkSession, folder: str, ids: list[int]) -> DataFrame:
    """scenario_id, ground: events of each scenario's users at 16 places along the axis, to which users are dealt."""
    own = table(spark, folder, "events").groupBy((F.col("user_id") % len(ids)).alias("k"), F.expr(f"user_id div {len(ids)} % {PLACES}").alias("place")).agg(F.count(F.lit(1)).alias("n"))
    held = own.groupBy("k").agg(F.map_from_entries(F.collect_list(F.struct("place", "n"))).alias("at"))
    every = spark.createDataFrame([(k, int(i)) for k, i in enumerate(ids)], "k bigint, scenario_id bigint").join(held, "k", "left")
    place = F.transform(F.sequence(F.lit(0).cast("bigint"), F.lit(PLACES - 1).cast("bigint")), lambda p: F.coalesce(F.element_at("at", p), F.lit(0)))
    return every.select("scenario_id", place.alias("ground"))


def policy_table_scenarios(spark: SparkSession, folder: str, regime: str = "restless", per_rank: int | None = None, seeds: int = 10) -> DataFrame:
    """All policies on held-out scenarios over recorded ground, hard boundaries, 100 events."""
    ids = [5 * k for k in range(1, seeds + 1)]
    return rollouts.policy_table(rollouts.synthetic(spark, ids, [2, 4, 8, 16], policies=EVERY, regime=regime, per_rank=per_rank, ground=recorded_ground(spark, folder, ids)))


add("policy_table_scenarios", policy_table_scenarios)
add("policy_table_calm", lambda s, d: policy_table_scenarios(s, d, "calm"))
add("policy_table_still", lambda s, d: policy_table_scenarios(s, d, "still", 200, 5))
add("end_to_end_calm", lambda s, d: measures.end_to_end(policy_table_scenarios(s, d, "calm")))
add("tradeoff", lambda s, d: measures.tradeoff(policy_table_scenarios(s, d)))

IDS, SCENARIO_STEPS, SCENARIO_M = 6, 100, 64


def _scenario_hash(*values: str | int) -> str:
    h = "17"
    for v in values:
        h = f"(({h}) * 48271::BIGINT + {v} + 11) % {PRIME}"
    return h


_BUMPS = " + ".join(
    f"(greatest(0, (50 + ({_scenario_hash(2026, 'a', 10 * k + 3)}) % 150{' + 20 * (t // 12)' if k == 1 else ''}) * (w{k} - abs(z - (({_scenario_hash(2026, 'a', 10 * k)}) % {SCENARIO_M} + ({_scenario_hash(2026, 'a', 10 * k + 1)}) % 5 * t * {SCENARIO_M} // 400) % {SCENARIO_M}))) // w{k})"
    for k in (1, 2)
)
_WIDE = ", ".join(f"{SCENARIO_M // 20} + ({_scenario_hash(2026, 'a', 10 * k + 2)}) % {SCENARIO_M // 5} AS w{k}" for k in (1, 2))
SCENARIO_SQL = f"""SELECT a AS scenario_id, t::INTEGER AS step, z::INTEGER AS slice_id, (CASE WHEN hit % 20 = 0 AND z * 10 // {SCENARIO_M} = hit % 10 THEN 2 ELSE 1 END * (100 + {_BUMPS}))::BIGINT AS work
FROM (SELECT a, t, z, {_WIDE}, {_scenario_hash(2027, 'a', 't')} AS hit FROM range({IDS}) x(a), range({SCENARIO_STEPS}) y(t), range({SCENARIO_M}) v(z))"""


def scenario_loads(spark: SparkSession, folder: str) -> DataFrame:
    """Scenarios on the ground of recorded events, whose users are dealt to scenarios and slices."""
    place = F.expr(f"user_id div {IDS} % {SCENARIO_M}")
    ground = table(spark, folder, "events").groupBy((F.col("user_id") % IDS).alias("scenario_id"), place.alias("slice_id")).agg(F.count(F.lit(1)).alias("n"))
    return portable_loads(spark, IDS, SCENARIO_STEPS, SCENARIO_M, ground=ground)


_GROUND_SQL = f"LEFT JOIN (SELECT user_id % {IDS} AS ga, user_id // {IDS} % {SCENARIO_M} AS gz, count(*) AS n FROM events GROUP BY ALL) ON ga = a AND gz = z"
add("scenario_loads", scenario_loads, SCENARIO_SQL.replace("(100 + ", "(coalesce(n, 0) + ") + " " + _GROUND_SQL)


def combine_step_grid(spark: SparkSession, folder: str) -> DataFrame:
    """Bounded steps over a grid of proposals and residuals, in SQL functions: the pairs of quantity and tax that lines have."""
    lines = table(spark, folder, "lineitem").select(F.col("l_quantity").cast("bigint").alias("q"), F.round(F.col("l_tax") * 100).cast("bigint").alias("t")).distinct()
    grid = lines.select(((F.col("q") - 25) / 2.0).alias("reactive"), ((F.col("t") - 4) / 2.0).alias("residual"))
    inside = F.least(F.greatest(F.col("reactive") / 8.0, F.lit(-1 + 1e-6)), F.lit(1 - 1e-6))
    return grid.select("reactive", "residual", F.round(8.0 * F.tanh(F.atanh(inside) + F.col("residual")), 6).alias("step"))


add("combine_step_grid", combine_step_grid, "WITH g AS (SELECT DISTINCT (CAST(l_quantity AS BIGINT) - 25) / 2.0::DOUBLE AS reactive, (CAST(round(l_tax * 100) AS BIGINT) - 4) / 2.0::DOUBLE AS residual FROM lineitem) SELECT reactive, residual, round(8.0 * tanh(atanh(least(greatest(reactive / 8.0, -1 + 1e-6), 1 - 1e-6)) + residual), 6) AS step FROM g")

CASES = [([0, 10, 20, 30], [8, -9], 6), ([0, 10, 20, 30], [-20, 20], 4), ([0, 4, 8], [6], 1), ([0, 5, 10, 15, 20], [3, 3, 3], 2)]


def sweep_cases(spark: SparkSession, folder: str) -> DataFrame:
    """The sweep as one fold over an array, on worked cases."""
    rows = spark.createDataFrame([(k, b, s, w) for k, (b, s, w) in enumerate(CASES)], "case int, bounds array<int>, steps array<int>, least int")
    fold = "aggregate(sequence(1, size(steps)), array(0), (o, b) -> concat(o, array(least(greatest(bounds[b] + steps[b - 1], o[b - 1] + least), bounds[b + 1] - least))), o -> concat(o, array(bounds[size(bounds) - 1])))"
    return rows.select("case", F.explode(F.expr(fold)).alias("bound"))


def _cases(rows: list[tuple]) -> str:
    return ", ".join("(" + ", ".join(f"{v}::BIGINT[]" if isinstance(v, list) else str(v) for v in (k, *r)) + ")" for k, r in enumerate(rows))


add(
    "sweep_cases",
    sweep_cases,
    f"""WITH RECURSIVE c(k, b, s, w) AS (VALUES {_cases(CASES)}), r AS (SELECT k, 1 AS i, [0::BIGINT] AS o FROM c UNION ALL
  SELECT k, i + 1, list_append(o, least(greatest(b[i + 1] + s[i], o[i] + w), b[i + 2] - w)) FROM r JOIN c USING (k) WHERE i <= len(s))
SELECT k AS "case", unnest(list_append(o, b[-1]))::INTEGER AS bound FROM r JOIN c USING (k) WHERE i = len(s) + 1""",
)


def scaling_model(spark: SparkSession, folder: str) -> DataFrame:
    """Modelled strong scaling: the largest share of work on P ranks, speed-up and efficiency (W2). One histogram serves all P."""
    counts = F.explode(F.array(*(F.lit(p) for p in (1, 2, 4, 8, 16))))
    ranked = partitioner.balanced_for(histogram(spark, folder, "order").withColumn("p", counts))
    times = ranked.groupBy("p", "rank").agg(F.sum("work").alias("w")).groupBy("p").agg(F.max("w").alias("t"))
    return measures.speedup(times.withColumn("case", F.lit("order"))).select("p", F.col("t").cast("bigint").alias("t"), F.round("speedup", 6).alias("speedup"), F.round("efficiency", 6).alias("efficiency"))


_PARTS = " UNION ALL ".join(f"(WITH {sql.ranked('midpoint', p, M)} SELECT {p} AS p, max(w)::BIGINT AS t FROM (SELECT sum(work) AS w FROM g GROUP BY rank))" for p in (1, 2, 4, 8, 16))
add("scaling_model", scaling_model, f"WITH {sql.histogram('order', 5000, M)}, s AS ({_PARTS}) SELECT p, t, round((SELECT t FROM s WHERE p = 1)::DOUBLE / t, 6) AS speedup, round((SELECT t FROM s WHERE p = 1)::DOUBLE / t / p, 6) AS efficiency FROM s")
BATCH_SLICES = 4096


def document_batches(spark: SparkSession, folder: str) -> DataFrame:
    """Ranges of ids with equal numbers of characters: a histogram of fixed length, however many documents (W12)."""
    docs = table(spark, folder, "documents")
    span = docs.agg(F.min("doc_id").alias("lo"), (F.max("doc_id") - F.min("doc_id") + 1).alias("n"))
    sliced = docs.join(F.broadcast(span)).groupBy(F.expr(f"int((doc_id - lo) * {BATCH_SLICES} div n)").alias("slice_id"))
    held = sliced.agg(F.sum("n_chars").cast("bigint").alias("work"), F.count(F.lit(1)).alias("n_cells"))
    return partitioner.balanced(held, RANKS).groupBy("rank").agg(F.sum("work").cast("bigint").alias("work"))


add(
    "document_batches",
    document_batches,
    f"WITH x AS (SELECT min(doc_id) AS lo, max(doc_id) - min(doc_id) + 1 AS n FROM documents), h AS (SELECT ((doc_id - lo) * {BATCH_SLICES} // n)::INTEGER AS slice_id, sum(n_chars)::BIGINT AS work, count(*)::BIGINT AS n_cells FROM documents, x GROUP BY 1), {sql.ranked('midpoint', RANKS, M)} SELECT rank, sum(work)::BIGINT AS work FROM g GROUP BY rank",
)


def moving_front(spark: SparkSession, folder: str) -> DataFrame:
    """Elements alive in a trailing window: the hot region sweeps over the axis (W11)."""
    born = order_tissue(spark, folder).select(F.expr("datediff(born, date'1992-01-01') div 30").cast("int").alias("slice_id"))
    return born.select("slice_id", F.explode(F.sequence("slice_id", F.col("slice_id") + 5)).alias("step")).groupBy("step", "slice_id").agg(F.count(F.lit(1)).alias("work"))


add("moving_front", moving_front, f"WITH {sql.elements('order')}, b AS (SELECT (date_diff('day', DATE '1992-01-01', born) // 30)::INTEGER AS slice_id FROM e) SELECT (slice_id + i)::INTEGER AS step, slice_id, count(*)::BIGINT AS work FROM b, range(6) r(i) GROUP BY ALL")


def ablation(spark: SparkSession, folder: str) -> DataFrame:
    """tau, alpha, step bound (in units of its default) and direction mode on held-out scenarios (W9), one row each, averaged over seeds.

    The reactive rule never steps away from the slower rank, so the mode is varied for the learned policy.
    """
    settings = [("reactive", t, a, m, "guarded") for t in (0.0, 0.02, 0.05, 0.1) for a in (0.25, 0.5, 1.0) for m in (1.0, 2.0)]
    settings += [("learned", 0.02, 0.5, m, mode) for m in (0.5, 1.0, 2.0) for mode in ("guarded", "free")]
    kinds = "policy string, tau double, alpha double, max_step double, mode string"
    weights, ids = gru.dumps(gru.trained()), [5 * k for k in range(1, 6)]

    def run(part: pd.DataFrame) -> pd.DataFrame:
        r, ranks, out = part.iloc[0], 8, []
        for one_of in r.grounds:
            one = scenario(int(one_of["scenario_id"]), 100, ranks, ground=one_of["ground"])
            rule = balance.Rule(tau=r.tau, alpha=r.alpha, mode=r["mode"])
            out.append(summary(rollout(one, r.policy, gru.loads(weights), rule, most=r.max_step * bound_of_step(one.slices, ranks))))
        return part.drop(columns="grounds").assign(mean_imbalance=float(np.mean([o["mean_imbalance"] for o in out])), moved=float(np.mean([o["moved"] for o in out])))

    grounds = recorded_ground(spark, folder, ids).agg(F.sort_array(F.collect_list(F.struct("scenario_id", "ground"))).alias("grounds"))  # one row
    grid = spark.createDataFrame(settings, kinds)
    return grid.join(F.broadcast(grounds)).groupBy(*grid.columns).applyInPandas(run, f"{kinds}, mean_imbalance double, moved double")


add("ablation", ablation)

#: 40 slices are cut where these shares of a group's events end, by value; ranks have 5 slices at least.
NARROW, GROUPS, NARROWEST = ("value < 1", "value < 100", "value < 150"), 12, 5


def min_width_repair(spark: SparkSession, folder: str) -> DataFrame:
    """Bounds moved forward, then backward, until no rank is too narrow: two folds over an array. Bounds are shares of groups of users' events."""
    cuts = ", ".join(f"int(count_if({test}) * 40 div count(*))" for test in NARROW)
    rows = table(spark, folder, "events").groupBy(F.expr(f"int(user_id % {GROUPS})").alias("case")).agg(F.expr(f"array(0, {cuts}, 40)").alias("bounds"), F.lit(NARROWEST).alias("least"))
    forward = "aggregate(slice(bounds, 2, size(bounds) - 2), array(0), (o, b) -> concat(o, array(greatest(b, element_at(o, -1) + least))), o -> concat(o, array(element_at(bounds, -1))))"
    backward = "aggregate(reverse(slice(f, 2, size(f) - 2)), array(element_at(f, -1)), (o, b) -> concat(array(least(b, o[0] - least)), o), o -> concat(array(0), o))"
    return rows.withColumn("f", F.expr(forward)).select("case", F.explode(F.expr(backward)).alias("bound"))


add(
    "min_width_repair",
    min_width_repair,
    f"""WITH RECURSIVE c(k, b, w) AS (SELECT (user_id % {GROUPS})::INTEGER, [0::BIGINT, {', '.join(f'count(*) FILTER ({test}) * 40 // count(*)' for test in NARROW)}, 40], {NARROWEST} FROM events GROUP BY 1), f AS (SELECT k, 1 AS i, [0::BIGINT] AS o FROM c UNION ALL
  SELECT k, i + 1, list_append(o, greatest(b[i + 1], o[i] + w)) FROM f JOIN c USING (k) WHERE i < len(b) - 1),
g AS (SELECT k, len(b) - 1 AS i, [b[-1]] AS o FROM c UNION ALL
  SELECT k, g.i - 1, list_prepend(least(f.o[g.i], g.o[1] - w), g.o) FROM g JOIN c USING (k) JOIN f USING (k) WHERE f.i = len(b) - 1 AND g.i > 1)
SELECT k AS "case", unnest(list_prepend(0, o))::INTEGER AS bound FROM g WHERE i = 1""",
)
