"""Interaction work of cells and slices."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import grid


def cells(elements: DataFrame, cutoff: float) -> DataFrame:
    """Each cell's element count, centroid (rounded down) and the centroid's bin."""
    centre = {f"c{a}": F.floor(F.sum(a) / F.count(F.lit(1))).cast("bigint") for a in grid.AXES}
    out = elements.groupBy("cell_id").agg(F.count(F.lit(1)).alias("n_elements"), *(c.alias(n) for n, c in centre.items()))
    return out.withColumns({b: grid.bin_of(F.col(f"c{a}"), cutoff) for a, b in zip(grid.AXES, grid.BINS, strict=True)})


def cell_work(elements: DataFrame, cutoff: float, variant: str = "centroid") -> DataFrame:
    """cell_id, cx, work: own elements times the elements in the 27 bins around the cell.

    'centroid' looks around the bin of the cell's centroid; 'per_element' adds up the
    neighbourhoods of its elements and so counts candidate tests exactly.
    """
    around = grid.spread(grid.bins(elements, cutoff), grid.offsets()).groupBy(*grid.BINS).agg(F.sum("n").alias("n_near"))
    own = cells(elements, cutoff)
    if variant == "centroid":
        scored = own.join(around, list(grid.BINS), "left")
        return scored.select("cell_id", "cx", "n_elements", (F.col("n_elements") * F.coalesce("n_near", F.lit(0))).cast("bigint").alias("work"))
    part = grid.with_bins(elements, cutoff).groupBy("cell_id", *grid.BINS).agg(F.count(F.lit(1)).alias("n"))
    exact = part.join(around, list(grid.BINS)).groupBy("cell_id").agg(F.sum(F.col("n") * F.col("n_near")).cast("bigint").alias("work"))
    return own.select("cell_id", "cx", "n_elements").join(exact, "cell_id")


def extent(elements: DataFrame, cutoff: float, axis: str = "x") -> tuple[int, int]:
    """The padded range of the axis: two numbers."""
    low, high = elements.agg(F.min(axis), F.max(axis)).first()
    return (0, 1) if low is None else (low - int(cutoff), high + int(cutoff))


def slice_of(position: Column, low: int, high: int, m: int) -> Column:
    """Which of m equal slices of [low, high) holds a position."""
    return F.floor((position - low) * F.lit(m) / F.lit(float(high - low))).cast("int")


def slice_histogram(scored: DataFrame, low: int, high: int, m: int, position: str = "cx") -> DataFrame:
    """slice_id, work and n_cells of all m slices, empty ones too."""
    sums = scored.groupBy(slice_of(F.col(position), low, high, m).alias("slice_id")).agg(F.sum("work").cast("bigint").alias("work"), F.count(F.lit(1)).alias("n_cells"))
    every = scored.sparkSession.range(m).select(F.col("id").cast("int").alias("slice_id"))
    return every.join(sums, "slice_id", "left").select("slice_id", F.coalesce("work", F.lit(0)).alias("work"), F.coalesce("n_cells", F.lit(0)).alias("n_cells"))


def choose_axis(elements: DataFrame, cutoff: float) -> str:
    """The axis that is longest in cutoffs."""
    row = elements.agg(*(F.max(a) - F.min(a) for a in grid.AXES)).first()
    return max(zip(row, grid.AXES, strict=True), key=lambda x: (x[0] / cutoff, -grid.AXES.index(x[1])))[1]
