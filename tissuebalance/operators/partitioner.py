"""Contiguous ranks of slices: uniform, count-balanced, work-aware and bottleneck-optimal cuts.

A histogram has at most about 1e5 slices whatever the tissue, so ordered windows over it and
lists of its numbers on the driver are of fixed size.
"""

from __future__ import annotations

from itertools import accumulate

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def uniform(histogram: DataFrame, ranks: int, m: int) -> DataFrame:
    return histogram.withColumn("rank", F.floor(F.col("slice_id") * ranks / F.lit(m)).cast("int"))


def balanced(histogram: DataFrame, ranks: int, rule: str = "midpoint", weight: str = "work") -> DataFrame:
    """Ranks by accumulated weight, in whole numbers.

    midpoint: the share in which a slice's middle falls; ceil: the share in which it ends;
    floor: the share in which it begins; nearest: each cut at the edge whose accumulated weight
    is nearest to its share, the left one of two equals, which is where midpoint cuts too. Slices
    without weight stay on the side of a share on which they lie.
    """
    return balanced_for(histogram.withColumn("p", F.lit(ranks)), rule, weight).drop("p")


def balanced_for(histogram: DataFrame, rule: str = "midpoint", weight: str = "work") -> DataFrame:
    """The same for several numbers of ranks at once, given with each row as p."""
    w = Window.partitionBy("p")
    upto = F.sum(weight).over(w.orderBy("slice_id").rowsBetween(Window.unboundedPreceding, 0))
    held = histogram.withColumns({"_upto": upto.cast("bigint"), "_total": F.sum(weight).over(w).cast("bigint"), "_n": F.count(F.lit(1)).over(w)})
    middle = 2 * F.col("_upto") - F.col(weight)
    twice = {"midpoint": middle, "nearest": middle, "ceil": 2 * F.col("_upto") - 1, "floor": 2 * (F.col("_upto") - F.col(weight))}[rule]
    share = F.expr("case when _total = 0 then slice_id * p div _n else _twice * p div (2 * _total) end")
    ranked = held.withColumn("_twice", twice.cast("bigint")).withColumn("rank", F.greatest(F.lit(0), F.least(F.col("p") - 1, share)).cast("int"))
    return ranked.drop("_upto", "_twice", "_total", "_n")


def count_balanced(histogram: DataFrame, ranks: int) -> DataFrame:
    """Equal numbers of cells: what a range partitioner of rows does."""
    return balanced(histogram, ranks, weight="n_cells")


def shares(ranked: DataFrame, ranks: int) -> DataFrame:
    """Work, slices and the share in millionths of each rank."""
    own = ranked.groupBy("rank").agg(F.sum("work").cast("bigint").alias("work"), F.count(F.lit(1)).alias("n_slices"), F.min("slice_id").alias("first_slice"), F.max("slice_id").alias("last_slice"))
    total = F.sum("work").over(Window.partitionBy())
    return own.withColumn("share_ppm", F.floor(F.try_divide(F.col("work") * F.lit(1000000.0), total)).cast("bigint"))


def bounds_of(work: list[int], ranks: int) -> list[int]:
    """The midpoint cut of a list: ranks + 1 slice numbers from 0 to its length."""
    total, out, at = sum(work), [0], 0
    upto = list(accumulate(work))
    for r in range(1, ranks):
        while at < len(work) and ((2 * upto[at] - work[at]) * ranks < 2 * total * r if total else at * ranks < len(work) * r):
            at += 1
        out.append(at)
    return [*out, len(work)]


def enforce_min_width(bounds: list[int], least: int) -> list[int]:
    """The nearest bounds, moved forward then backward, with no rank narrower than least."""
    out = list(bounds)
    if least * (len(out) - 1) > out[-1]:
        raise ValueError("no room for that many ranks of that width")
    for k in range(1, len(out) - 1):
        out[k] = max(out[k], out[k - 1] + least)
    for k in range(len(out) - 2, 0, -1):
        out[k] = min(out[k], out[k + 1] - least)
    return out


def optimal_bounds(work: list[int], ranks: int) -> list[int]:
    """Bounds of contiguous groups none of which exceeds the smallest possible largest share."""
    most, out, own = optimal(work, ranks), [0], 0
    for k, w in enumerate(work):
        if own + w > most:
            out.append(k)
            own = 0
        own += w
    return [*out, *[len(work)] * (ranks + 1 - len(out))]


def optimal(work: list[int], ranks: int) -> int:
    """The smallest possible largest share over contiguous groups."""
    low, high = max(work, default=0), sum(work)
    while low < high:
        middle, groups, own = (low + high) // 2, 1, 0
        for w in work:
            groups, own = (groups + 1, w) if own + w > middle else (groups, own + w)
        low, high = (low, middle) if groups <= ranks else (middle + 1, high)
    return low
