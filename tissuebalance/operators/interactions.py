"""Pairs within the cutoff: serial and parallel all-pairs, binned joins and a slab kernel.

A pair of different elements contributes when its distance is at most the cutoff. Every
evaluator gives the same pairs; they differ in the tests they need.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import ghosts, grid

ID = ("cell_id", "element_no")
#: Below this many elements the quadratic test costs no more than a join's shuffles.
SMALL = 1000
#: Planes of bins in a run of the sweeps, which is what a task gets of a rank at the least.
PLANES = 8


def sides(elements: DataFrame, *more: str) -> tuple[DataFrame, DataFrame]:
    names = [*ID, *grid.AXES, *more]
    return tuple(elements.select(*(F.col(n).alias(f"{n}{s}") for n in names)) for s in ("_a", "_b"))


def squared() -> Column:
    return sum((F.pow(F.col(f"{p}_a") - F.col(f"{p}_b"), 2) for p in grid.AXES), F.lit(0.0))


def different() -> Column:
    return (F.col("cell_id_a") != F.col("cell_id_b")) | (F.col("element_no_a") != F.col("element_no_b"))


def all_pairs(elements: DataFrame, cutoff: float, most: int = 200_000) -> DataFrame:
    """The parallel quadratic baseline, for comparison on at most `most` elements."""
    n = elements.count()
    if n > most:
        raise ValueError(f"{n} elements are too many for all pairs; use all_pairs_tiled or binned")
    a, b = sides(elements)
    return a.crossJoin(b).where(different() & (squared() <= float(cutoff) ** 2))


def all_pairs_tiled(elements: DataFrame, cutoff: float, tile: int = 2048) -> DataFrame:
    """Contributing pairs per element from blocks of tile x tile tests: quadratic, in tasks of one size."""
    tiles = max(1, -(-elements.count() // tile))
    own = F.pmod(F.xxhash64(*ID), F.lit(tiles)).cast("int")  # as every: a cogroup takes keys of two types to different tasks
    every = F.explode(F.sequence(F.lit(0), F.lit(tiles - 1)))
    a = elements.select(own.alias("i"), every.alias("j"), *ID, *grid.AXES)
    b = elements.select(every.alias("i"), own.alias("j"), *ID, *grid.AXES)

    def run(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        mine, at = left[list(grid.AXES)].to_numpy(np.int64), right[list(grid.AXES)].to_numpy(np.int64)
        found = np.array([(((at - x) ** 2).sum(axis=1) <= cutoff * cutoff).sum() for x in mine], np.int64)
        if len(left) and left["i"].iloc[0] == left["j"].iloc[0]:
            found -= 1  # itself
        return left[list(ID)].assign(n_pairs=found)

    part = a.groupBy("i", "j").cogroup(b.groupBy("i", "j")).applyInPandas(run, "cell_id bigint, element_no bigint, n_pairs bigint")
    return part.groupBy(*ID).agg(F.sum("n_pairs").alias("n_pairs"))


def all_pairs_serial(elements: DataFrame, cutoff: float) -> DataFrame:
    """Contributing pairs per element from one task that tests every pair: the baseline that time rules out, not a limit."""

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(parts), ignore_index=True)
        at = rows[list(grid.AXES)].to_numpy(np.int64)
        found = np.zeros(len(rows), np.int64)
        for i in range(len(rows)):
            found[i] = (((at - at[i]) ** 2).sum(axis=1) <= cutoff * cutoff).sum() - 1
        yield rows[list(ID)].assign(n_pairs=found)

    return elements.select(*ID, *grid.AXES).coalesce(1).mapInPandas(run, "cell_id bigint, element_no int, n_pairs bigint")


def binned(elements: DataFrame, cutoff: float, stencil: str = "full", per_cutoff: int = 1, carry: tuple[str, ...] = ()) -> DataFrame:
    """Ordered pairs from an equality join on bins, the exact distance as a residual condition.

    stencil 'half' tests the own bin and the 13 that follow it, and mirrors what it finds.
    per_cutoff cuts bins finer: more bins to look at, fewer tests that fail. carry: columns of
    both elements that go along.
    """
    placed = grid.with_bins(elements, cutoff / per_cutoff)
    half = stencil == "half"
    kept = (*ID, *grid.AXES, *carry)
    a = grid.spread(placed.select(*kept, *grid.BINS), grid.offsets(per_cutoff, half))
    a = a.select(*(F.col(n).alias(f"{n}_a") for n in kept), *grid.BINS, "shift")
    b = placed.select(*(F.col(n).alias(f"{n}_b") for n in kept), *grid.BINS)
    met = a.join(b, list(grid.BINS)).where(squared() <= float(cutoff) ** 2)
    if not half:
        return met.where(different()).drop("shift", *grid.BINS)
    own = (F.col("shift.a") == 0) & (F.col("shift.b") == 0) & (F.col("shift.c") == 0)
    first = F.struct("cell_id_a", "element_no_a") < F.struct(F.col("cell_id_b").alias("cell_id_a"), F.col("element_no_b").alias("element_no_a"))
    once = met.where(~own | first).drop("shift", *grid.BINS)
    mirrored = once.select(*(F.col(c[:-1] + ("b" if c[-1] == "a" else "a")).alias(c) for c in once.columns))
    return once.unionByName(mirrored)


def pair_counts(pairs: DataFrame) -> DataFrame:
    """Contributing pairs of each element that has any."""
    return pairs.groupBy(F.col("cell_id_a").alias("cell_id"), F.col("element_no_a").alias("element_no")).agg(F.count(F.lit(1)).alias("n_pairs"))


def sites(elements: DataFrame, *more: str) -> DataFrame:
    """Distinct positions, by the columns more where given, and the number n of elements at each."""
    return elements.groupBy(*grid.AXES, *more).agg(F.count(F.lit(1)).alias("n"))


def met_sites(spots: DataFrame, cutoff: float, *more: str) -> DataFrame:
    """Ordered pairs of sites within the cutoff, a site and itself included, from the equality join on bins.

    Bins are two cutoffs wide, and a site goes to those alone that a sphere around it reaches: seven
    on average, where bins of one cutoff would take 27 copies of each site through the shuffle.
    """
    edge = 2 * float(cutoff)
    placed, kept = grid.with_bins(spots, edge), (*grid.AXES, *more)
    a = grid.reached(placed, edge, cutoff).select(*(F.col(c).alias(f"{c}_a") for c in kept), *grid.BINS)
    b = placed.select(*(F.col(c).alias(f"{c}_b") for c in kept), "n", *grid.BINS)
    return a.join(b, list(grid.BINS)).where(squared() <= float(cutoff) ** 2)


def binned_counts(elements: DataFrame, cutoff: float) -> DataFrame:
    """pair_counts of binned, with elements that lie together tested once: sites are joined, not elements.

    elements is read twice.
    """
    near = met_sites(sites(elements), cutoff).groupBy(*(F.col(f"{a}_a").alias(a) for a in grid.AXES)).agg((F.sum("n") - 1).alias("n_pairs"))
    return elements.join(near, list(grid.AXES)).where("n_pairs > 0").select(*ID, "n_pairs")


def candidate_counts(elements: DataFrame, cutoff: float, by: tuple[str, ...] = ()) -> DataFrame:
    """Elements, occupied bins and ordered candidate tests (self included) of each group, from bins alone."""
    near = grid.neighbourhood_counts(grid.bins(elements, cutoff, by), by)
    return near.groupBy(*by).agg(F.sum("n").cast("bigint").alias("elements"), F.count(F.lit(1)).alias("bins"), F.sum(F.col("n") * F.col("n_near")).cast("bigint").alias("candidates"))


def pair_work(elements: DataFrame, cutoff: float) -> DataFrame:
    """One row: candidate tests, pairs within the cutoff (both self included) and the share that is useful."""
    useful = binned(elements, cutoff).agg(F.count(F.lit(1)).alias("pairs"))
    row = candidate_counts(elements, cutoff).join(F.broadcast(useful)).withColumn("pairs", F.col("pairs") + F.col("elements"))
    return row.select("elements", "candidates", "pairs", F.try_divide(F.col("pairs").cast("double"), F.col("candidates")).alias("hit_rate"))


def dealt(elements: DataFrame, cutoff: float, bounds: list[float]) -> DataFrame:
    """Sites and ghosts at their ranks, in runs of PLANES planes of bins that have the plane on either side as ghosts too: one shuffle."""
    placed = grid.with_bins(ghosts.attach(elements.dropna(subset=list(grid.AXES)), bounds, cutoff), cutoff).drop("home_rank")
    own, left, right = (F.floor((F.col("bx") + d) / F.lit(float(PLANES))).cast("bigint") for d in (0, -1, 1))
    copies = placed.withColumn("run", F.explode(F.array_compact(F.array(own, F.when(left < own, left), F.when(right > own, right)))))
    parts = max(len(bounds) + 1, int(elements.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    rows = copies.withColumn("is_ghost", F.col("is_ghost") | (F.col("run") != own))
    return rows.repartitionById(parts, F.pmod(F.col("run"), F.lit(parts)).cast("int")).sortWithinPartitions("rank", "run", "bx")


def slab_counts(elements: DataFrame, cutoff: float, bounds: list[float]) -> DataFrame:
    """Contributing pairs and tests of each element, from slab_sites. elements is read twice.

    tests: the elements in the bins around; seconds: the time spent in the kernel, per element.
    """
    found = slab_sites(sites(elements), cutoff, bounds)
    out = elements.join(found, list(grid.AXES))
    return out.select("cell_id", F.col("element_no").cast("bigint").alias("element_no"), "n_pairs", "tests", "rank", (F.col("seconds") / F.col("n")).alias("seconds"))


def slab_sites(spots: DataFrame, cutoff: float, bounds: list[float]) -> DataFrame:
    """Contributing pairs and tests of an element at each site, from tasks that sweep the planes of bins of a rank, run by run.

    bounds: where ranks end on x (interior boundaries, at least a cutoff apart). A task holds
    three planes of bins at a time, so its memory does not grow with its rank; many tasks share a
    rank's runs, so that few ranks leave no core idle. seconds: the time spent in the kernel, per
    site; their sum is what a rank spends.
    """
    from .kernels import count_kernel, sweep_planes

    kernel = count_kernel(float(cutoff))
    rows = dealt(spots.select(*grid.AXES, "n"), cutoff, bounds)
    return rows.mapInPandas(lambda parts: sweep_planes(parts, kernel), "x bigint, y bigint, z bigint, n bigint, n_pairs bigint, tests bigint, rank int, seconds double")


def slab_forces(elements: DataFrame, cutoff: float, bounds: list[float]) -> DataFrame:
    """Velocity of each element, as mechanics.velocity gives it, from the same sweeps."""
    from . import mechanics

    moved = mechanics.velocity(elements.select(*ID, *grid.AXES, "cell_type"), cutoff, lambda spots: slab_push(spots, cutoff, bounds))
    return moved.select("cell_id", F.col("element_no").cast("bigint").alias("element_no"), "vx", "vy", "vz", "tests", "rank", "seconds")


def slab_push(spots: DataFrame, cutoff: float, bounds: list[float]) -> DataFrame:
    """What the forces between cells give an element at each site, as mechanics.push does, with tests, rank and seconds as slab_counts has them."""
    from .kernels import force_kernel, sweep_planes

    kernel = force_kernel(float(cutoff))
    rows = dealt(spots.select(*grid.AXES, "cell_type", "n"), cutoff, bounds)
    found = rows.mapInPandas(lambda parts: sweep_planes(parts, kernel), "x bigint, y bigint, z bigint, cell_type string, n bigint, vx double, vy double, vz double, tests bigint, rank int, seconds double")
    return found.withColumn("seconds", F.col("seconds") / F.col("n")).drop("n")


def evaluate(elements: DataFrame, cutoff: float, strategy: str = "auto") -> DataFrame:
    """Pairs by the evaluator that suits the number of elements."""
    if strategy == "auto":
        strategy = "all_pairs" if elements.count() < SMALL else "binned"
    return all_pairs(elements, cutoff) if strategy == "all_pairs" else binned(elements, cutoff)
