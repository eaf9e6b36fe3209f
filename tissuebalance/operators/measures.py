"""Measures of balance, migration and scaling, as DataFrame functions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .ghosts import rank_of


def rank_curves(loads: DataFrame, bounds: list[int]) -> DataFrame:
    """step, rank, t: the load of each rank under fixed slice bounds; loads: step, slice_id, work."""
    held = loads.groupBy("step", rank_of(F.col("slice_id"), bounds[1:-1]).alias("rank")).agg(F.sum("work").cast("bigint").alias("t"))
    every = loads.select("step").distinct().join(F.broadcast(loads.sparkSession.range(len(bounds) - 1).select(F.col("id").cast("int").alias("rank"))))
    return every.join(held, ["step", "rank"], "left").select("step", "rank", F.coalesce("t", F.lit(0)).alias("t"))


def local_imbalance(times: DataFrame) -> DataFrame:
    """step, boundary, t_left, t_right, i_local (null where both are 0)."""
    w = Window.partitionBy("step").orderBy("rank")
    both = times.withColumns({"t_right": F.lead("t").over(w), "boundary": F.col("rank") + 1}).where("t_right is not null").withColumnRenamed("t", "t_left")
    return both.select("step", "boundary", "t_left", "t_right", F.try_divide((F.col("t_right") - F.col("t_left")).cast("double"), (F.col("t_right") + F.col("t_left")) / 2.0).alias("i_local"))


def reactive_proposals(times: DataFrame, bounds: list[int], tau: float = 0.02, alpha: float = 0.5) -> DataFrame:
    """The reactive rule on every boundary, in SQL functions only."""
    pairs = local_imbalance(times)
    widths = F.array(*(F.lit(float(b - a)) for a, b in zip(bounds, bounds[1:], strict=False)))
    slow = F.when(F.col("t_right") > F.col("t_left"), F.get(widths, F.col("boundary"))).otherwise(F.get(widths, F.col("boundary") - 1))
    size = F.lit(alpha) * slow * F.abs(F.col("t_right") - F.col("t_left")) / (2.0 * F.greatest("t_left", "t_right"))
    return pairs.withColumn("proposal", F.when(F.abs("i_local") > tau, F.signum("i_local") * size).otherwise(0.0))


def global_imbalance(times: DataFrame) -> DataFrame:
    return times.groupBy("step").agg(F.try_divide((F.max("t") - F.min("t")).cast("double"), F.avg("t")).alias("i_global"), F.max("t").alias("t_max"))


def speedup(times: DataFrame) -> DataFrame:
    """p, t, speed-up and efficiency against p = 1; times: case, p, t."""
    one = F.first("t").over(Window.partitionBy("case").orderBy("p").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return times.withColumn("speedup", F.try_divide(one.cast("double"), F.col("t"))).withColumn("efficiency", F.col("speedup") / F.col("p"))


def loglog_slope(y: Column, x: Column) -> Column:
    return F.regr_slope(F.ln(y), F.ln(x))


def spread(times: DataFrame) -> DataFrame:
    """Of each step: the relative excess of the slowest rank and the spread of times, both over their mean."""
    mean = F.avg("t")
    return times.groupBy("step").agg(F.try_divide(F.max("t") - mean, mean).alias("excess"), F.try_divide(F.stddev_pop("t"), mean).alias("spread"))


def rank_times(log: DataFrame) -> DataFrame:
    """policy, ranks, scenario_id, step, rank, t: per-rank curves of a rollout log."""
    return log.select("policy", "ranks", "scenario_id", "step", F.posexplode("times").alias("rank", "t"))


def migration(log: DataFrame) -> DataFrame:
    """Slices and work moved over each whole rollout, the last event's included."""
    return log.groupBy("run_id").agg(F.sum("moved").cast("bigint").alias("moved"), F.sum("moved_work").alias("moved_work"))


def moved_slices(log: DataFrame) -> DataFrame:
    """Slices that change hands, one row each: run_id, step of the event after which they do, slice_id, from_rank, to_rank.

    Only slices between the old and the new place of some boundary are looked at.
    """
    after = F.lead("bounds").over(Window.partitionBy("run_id").orderBy("step"))
    pairs = log.withColumn("after", after).where("after is not null and after <> bounds")
    between = pairs.select("run_id", "step", "bounds", "after", F.explode(F.arrays_zip("bounds", "after")).alias("b")).where("b.bounds <> b.after")
    rows = between.select("run_id", "step", "bounds", "after", F.explode(F.sequence(F.least("b.bounds", "b.after"), F.greatest("b.bounds", "b.after") - 1)).alias("slice_id"))
    of = "aggregate({0}, -1, (n, b) -> n + int(b <= slice_id))"
    ranks = rows.select("run_id", "step", "slice_id", F.expr(of.format("bounds")).alias("from_rank"), F.expr(of.format("after")).alias("to_rank"))
    return ranks.where("from_rank <> to_rank").distinct()


def saving(runs: DataFrame, value: str, against: str) -> DataFrame:
    """Each policy's relative saving of a value against one policy of its rank count."""
    other = runs.where(F.col("policy") == against).select("ranks", F.col(value).alias("_other"))
    return runs.join(F.broadcast(other), "ranks").withColumn(f"{value}_saved", F.try_divide(F.col("_other") - F.col(value), F.col("_other"))).drop("_other")


def ratio(runs: DataFrame, value: str, of: str) -> DataFrame:
    """How many times a policy's value another's is, of the same rank count."""
    other = runs.where(F.col("policy") == of).select("ranks", F.col(value).alias("_other"))
    return runs.join(F.broadcast(other), "ranks").withColumn(f"{value}_ratio", F.try_divide(F.col("_other").cast("double"), F.col(value))).drop("_other")


def move_efficiency(runs: DataFrame) -> DataFrame:
    """Slices moved for each hundredth by which the mean imbalance falls below the static one."""
    other = runs.where("policy = 'static'").select("ranks", F.col("mean_imbalance").alias("_other"))
    gained = (F.col("_other") - F.col("mean_imbalance")) * 100
    return runs.join(F.broadcast(other), "ranks").withColumn("moves_per_point", F.when(gained > 0, F.col("moved") / gained)).drop("_other")


def end_to_end(runs: DataFrame) -> DataFrame:
    """The policy table with savings against static, moves against reactive, and moves per point gained."""
    return move_efficiency(ratio(saving(saving(runs, "runtime", "static"), "mean_imbalance", "static"), "moved", "reactive"))


def tradeoff(policies: DataFrame) -> DataFrame:
    """Marks policies that no other beats in imbalance and migration at once; policies: ranks, policy, mean_imbalance, moved.

    The rows of one rank count, one per policy, are compared in an array.
    """
    rows = policies.groupBy("ranks").agg(F.collect_list(F.struct("policy", "mean_imbalance", "moved")).alias("all"))
    beaten = "exists(all, o -> o.mean_imbalance <= x.mean_imbalance and o.moved <= x.moved and (o.mean_imbalance < x.mean_imbalance or o.moved < x.moved))"
    marked = rows.select("ranks", F.expr(f"inline(transform(all, x -> struct(x.policy as policy, x.mean_imbalance as mean_imbalance, x.moved as moved, not {beaten} as pareto)))"))
    return marked.select("ranks", "policy", "mean_imbalance", "moved", "pareto")
