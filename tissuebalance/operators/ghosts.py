"""Ranks along x, and the ghost margin each of them needs."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def rank_of(position: Column, bounds: list[float]) -> Column:
    """The rank that owns a position, by halving; bounds: interior boundaries, a position on one belongs to its right."""

    def search(low: int, high: int) -> Column:
        if low == high:
            return F.lit(low)
        middle = (low + high) // 2
        return F.when(position < F.lit(bounds[middle]), search(low, middle)).otherwise(search(middle + 1, high))

    return search(0, len(bounds)).cast("int")


def check_widths(bounds: list[float], cutoff: float) -> None:
    """Ranks narrower than the cutoff would need ghosts from beyond their neighbours."""
    for left, right in zip(bounds, bounds[1:], strict=False):
        if right - left < cutoff:
            raise ValueError(f"a rank from {left} to {right} is narrower than the cutoff of {cutoff}")


def attach(elements: DataFrame, bounds: list[float], cutoff: float) -> DataFrame:
    """Each element at its home rank, and as a ghost at a neighbour whose boundary is within the cutoff."""
    check_widths(bounds, cutoff)
    home = rank_of(F.col("x"), bounds)
    left = F.when(rank_of(F.col("x") - F.lit(float(cutoff)), bounds) < F.col("home_rank"), F.col("home_rank") - 1)
    right = F.when(rank_of(F.col("x") + F.lit(float(cutoff)), bounds) > F.col("home_rank"), F.col("home_rank") + 1)
    copies = elements.withColumn("home_rank", home).withColumn("rank", F.explode(F.array_compact(F.array("home_rank", left, right))))
    return copies.withColumn("is_ghost", F.col("rank") != F.col("home_rank"))


def min_width(cutoff: float, thickness: float) -> int:
    """Slices a rank needs so that only its neighbours can hold its ghosts."""
    return math.ceil(cutoff / thickness)


def assemble(placed: DataFrame) -> DataFrame:
    """The whole tissue again: owned elements only."""
    return placed.where(~F.col("is_ghost")).drop("is_ghost", "home_rank", "rank")
