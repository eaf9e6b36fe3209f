"""Cubic bins with the cutoff as edge, and their 27-bin neighbourhoods."""

from __future__ import annotations

from itertools import product

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

AXES = ("x", "y", "z")
BINS = ("bx", "by", "bz")


def bin_of(position: Column, edge: float) -> Column:
    return F.floor(position / F.lit(float(edge))).cast("bigint")


def with_bins(elements: DataFrame, edge: float) -> DataFrame:
    return elements.withColumns({b: bin_of(F.col(a), edge) for a, b in zip(AXES, BINS, strict=True)})


def offsets(reach: int = 1, half: bool = False) -> list[tuple[int, int, int]]:
    """All offsets within reach; half: the own bin and those that come after it in order."""
    every = product(range(-reach, reach + 1), repeat=3)
    return [o for o in every if not half or o >= (0, 0, 0)]


def spread(df: DataFrame, shifts: list[tuple[int, int, int]]) -> DataFrame:
    """Each row once for every offset, with shifted bins and the offset `shift`."""
    rows = F.explode(F.array(*(F.struct(*(F.lit(d).alias(n) for d, n in zip(o, "abc", strict=True))) for o in shifts)))
    moved = df.withColumn("shift", rows)
    return moved.withColumns({b: F.col(b) + F.col(f"shift.{n}") for b, n in zip(BINS, "abc", strict=True)})


def reached(placed: DataFrame, edge: float, cutoff: float) -> DataFrame:
    """Each row, which has its bins of an edge of at least the cutoff, once for every bin that a sphere of the cutoff around it reaches."""
    def gap(axis: str, b: str, n: str) -> Column:
        low = F.col(axis) - F.col(b) * F.lit(float(edge))
        return F.when(F.col(f"shift.{n}") < 0, low).when(F.col(f"shift.{n}") > 0, F.lit(float(edge)) - low).otherwise(0.0)

    rows = F.explode(F.array(*(F.struct(*(F.lit(d).alias(n) for d, n in zip(o, "abc", strict=True))) for o in offsets())))
    apart = sum((F.pow(gap(a, b, n), 2) for a, b, n in zip(AXES, BINS, "abc", strict=True)), F.lit(0.0))
    near = placed.withColumn("shift", rows).where(apart <= float(cutoff) ** 2)
    return near.withColumns({b: F.col(b) + F.col(f"shift.{n}") for b, n in zip(BINS, "abc", strict=True)}).drop("shift")


def bins(elements: DataFrame, edge: float, by: tuple[str, ...] = ()) -> DataFrame:
    """Occupied bins of each group and their numbers of elements."""
    return with_bins(elements, edge).groupBy(*by, *BINS).agg(F.count(F.lit(1)).alias("n"))


def neighbourhood_counts(occupied: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """n_near: elements in the 27 bins around each occupied bin. Only bins are shuffled, never elements."""
    around = spread(occupied, offsets()).groupBy(*by, *BINS).agg(F.sum("n").alias("n_near"))
    return occupied.join(around, [*by, *BINS])
