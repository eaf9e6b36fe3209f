"""Element forces, moves, growth, division and tissue snapshots."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from . import grid, interactions
from ..functions.forces import INTER, INTRA, MEMBRANE, OTHER_TYPE
from ..sources.scratch import settled


def pair_force(r: Column, same_cell: Column, same_type: Column) -> Column:
    """Repulsion less attraction along the separation, r in cutoffs."""
    def strength(u: float, v: Column | float, near: float, far: float) -> Column:
        return F.lit(u / near) * F.exp(-r / near) - F.lit(1.0 / far) * v * F.exp(-r / far)

    u, v, near, far = INTRA
    inter = F.when(same_type, INTER[1]).otherwise(INTER[1] * OTHER_TYPE)
    return F.when(same_cell, strength(u, F.lit(v), near, far)).otherwise(strength(INTER[0], inter, INTER[2], INTER[3]))


def push(spots: DataFrame, cutoff: float) -> DataFrame:
    """vx, vy, vz that the forces between cells give an element at each site that has others near, from the join on bins."""
    met = interactions.met_sites(spots, cutoff, "cell_type").where(interactions.squared() > 0)
    r = F.sqrt(interactions.squared())
    f = F.col("n") * pair_force(r / float(cutoff), F.lit(False), F.col("cell_type_a").eqNullSafe(F.col("cell_type_b"))) / r
    own = met.withColumn("f", f).groupBy(*(F.col(f"{c}_a").alias(c) for c in (*grid.AXES, "cell_type")))
    return own.agg(*(F.sum(F.col("f") * (F.col(f"{p}_a") - F.col(f"{p}_b"))).alias(f"v{p}") for p in grid.AXES))


def own_cell(elements: DataFrame, cutoff: float) -> DataFrame:
    """Elements with ux, uy, uz: what the forces of their cell's other elements are more than those between cells would be.

    The window puts a cell's elements side by side and tells how many they are; the order tissue lies so already.
    """
    from .kernels import cell_pushes

    sized = elements.withColumn("_n", F.count(F.lit(1)).over(Window.partitionBy("cell_id")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in whole_cells(batches):
            known = np.logical_and.reduce([rows.column(a).is_valid().to_numpy() for a in grid.AXES])
            at = [rows.column(a).fill_null(0).to_numpy() for a in grid.AXES]
            kinds = pc.dictionary_encode(rows.column("cell_type").combine_chunks(), null_encoding="encode").indices.to_numpy()
            sizes = rows.column("_n").to_numpy()
            firsts, k = np.zeros(len(sizes), np.int64), 0
            while k < len(sizes):
                firsts[k : k + sizes[k]] = k
                k += sizes[k]
            out = rows.drop_columns(["_n"])
            for name, got in zip(("ux", "uy", "uz"), cell_pushes(at, kinds, known, firsts, sizes, float(cutoff)).T, strict=True):
                out = out.append_column(name, pa.array(np.ascontiguousarray(got)))
            yield from out.combine_chunks().to_batches()

    return sized.mapInArrow(run, StructType([*elements.schema.fields, *(StructField(f"u{a}", DoubleType()) for a in grid.AXES)]))


def whole_cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """The rows of batches, cut between cells; _n: the number of rows of each cell, which stand together."""
    held, rows, end = [], 0, 0  # end: where the last cell that has begun will end
    for batch in batches:
        held.append(batch)
        sizes, begin, cut = batch.column("_n").to_pylist(), rows, 0
        rows += batch.num_rows
        while end < rows:
            cut = end
            end += sizes[end - begin]
        cut = rows if end == rows else cut
        if cut:
            whole = pa.Table.from_batches(held)
            yield whole.slice(0, cut)
            held, rows, end = whole.slice(cut).to_batches(), rows - cut, end - cut


def velocity(elements: DataFrame, cutoff: float, pushes: Callable[[DataFrame], DataFrame] | None = None, floor: int | None = None) -> DataFrame:
    """Each element's velocity: pair forces of its neighbourhood and the pull of the membrane below.

    Within a cell types play no part; between cells those of the two elements do. Elements of one
    position and type get the same push from other cells, so pushes (default: push) is asked once
    for each such site, as if all were cells of their own; own_cell sets right what lies in the same cell.
    """
    held = settled(own_cell(elements, cutoff))
    pushes = pushes or (lambda spots: push(spots, cutoff))
    pushed = settled(pushes(interactions.sites(held, "cell_type")))
    if floor is None:
        floor = held.agg(F.min("z")).first()[0]
    g, reach = MEMBRANE
    pull = F.lit(-g / reach) * F.exp(-(F.col("z") - F.lit(floor)) / (reach * float(cutoff)))
    site = (*grid.AXES, "cell_type")
    to = pushed.withColumnsRenamed({c: f"{c}_to" for c in site})
    moved = held.join(to, [F.col(c).eqNullSafe(F.col(f"{c}_to")) for c in site], "left").drop(*(f"{c}_to" for c in site))
    whole = {f"v{p}": F.coalesce(f"v{p}", F.lit(0.0)) + F.col(f"u{p}") for p in grid.AXES}
    whole["vz"] = whole["vz"] + pull
    return moved.withColumns(whole).drop("ux", "uy", "uz")


def step(elements: DataFrame, cutoff: float, dt: float, pushes: Callable[[DataFrame], DataFrame] | None = None, floor: int | None = None) -> DataFrame:
    """One explicit Euler step, positions in whole units."""
    moved = velocity(elements, cutoff, pushes, floor)
    return moved.withColumns({p: (F.col(p) + F.floor(F.col(f"v{p}") * dt + 0.5)).cast("bigint") for p in grid.AXES}).drop("vx", "vy", "vz")


def grow(elements: DataFrame, most: int = 8) -> DataFrame:
    """Each cell below `most` elements gains one at its centroid (rounded down)."""
    centre = elements.groupBy("cell_id").agg((F.max("element_no") + 1).cast("int").alias("element_no"), *(F.floor(F.sum(a) / F.count(F.lit(1))).cast("bigint").alias(a) for a in grid.AXES), F.first("cell_type").alias("cell_type"), F.max("born").alias("born"), F.count(F.lit(1)).alias("n")).where(F.col("n") < most)
    return elements.unionByName(centre.drop("n"))


def divide(elements: DataFrame, threshold: int = 6) -> DataFrame:
    """Cells of at least threshold elements split at the median of their longest axis.

    Daughters are 2 * id and 2 * id + 1, with parent_id; other cells keep their id times two.
    """
    own = Window.partitionBy("cell_id")
    spans = [F.max(a).over(own) - F.min(a).over(own) for a in grid.AXES]
    longest = F.when((spans[0] >= spans[1]) & (spans[0] >= spans[2]), F.col("x")).when(spans[1] >= spans[2], F.col("y")).otherwise(F.col("z"))
    sized = elements.withColumns({"n": F.count(F.lit(1)).over(own), "along": longest})
    place = F.row_number().over(Window.partitionBy("cell_id").orderBy("along", "element_no"))
    second = (F.col("n") >= threshold) & (2 * F.col("place") > F.col("n"))
    out = sized.withColumn("place", place).withColumn("parent_id", F.when(F.col("n") >= threshold, F.col("cell_id")))
    return out.withColumn("cell_id", F.col("cell_id") * 2 + second.cast("int")).drop("n", "along", "place")


def generations(elements: DataFrame, thresholds: list[int]) -> tuple[DataFrame, DataFrame]:
    """The tissue after one division round for each threshold, and the edges of its lineage: generation, parent, child.

    A cell that does not divide has one child, itself under its new number.
    """
    edges = None
    for k, threshold in enumerate(thresholds):
        elements = divide(elements.drop("parent_id"), threshold)
        own = elements.select(F.lit(k + 1).alias("generation"), F.expr("cell_id div 2").alias("parent"), F.col("cell_id").alias("child")).distinct()
        edges = own if edges is None else edges.unionByName(own)
    return elements, edges


def lineage(edges: DataFrame) -> DataFrame:
    """ancestor, descendant, generation of the first and number of generations between, from edges (generation, parent, child).

    One join for each generation after the first, of which the driver reads the number: a recursive
    query stops at a million rows.
    """
    low, high = edges.agg(F.min("generation"), F.max("generation")).first()
    own = edges.select(F.col("parent").alias("ancestor"), F.col("child").alias("descendant"), F.col("generation").alias("since"), F.lit(1).alias("generations"))
    out, after = own, edges.select(F.col("generation").alias("upto"), F.col("parent").alias("descendant"), "child")
    for _ in range((high or 0) - (low or 0)):
        own = own.withColumn("upto", F.col("since") + F.col("generations")).join(after, ["descendant", "upto"])
        own = own.select("ancestor", F.col("child").alias("descendant"), "since", (F.col("generations") + 1).alias("generations"))
        out = out.unionByName(own)
    return out


def differentiate(cells: DataFrame, rules: list[tuple[Column, str]]) -> DataFrame:
    """Cell types by the first rule that holds; rules may use layer (z), age (born) or any other column."""
    kind = F.col("cell_type")
    for test, name in reversed(rules):
        kind = F.when(test, F.lit(name)).otherwise(kind)
    return cells.withColumn("cell_type", kind)


def snapshots(elements: DataFrame, times: int = 6) -> DataFrame:
    """Elements and cells alive at `times` equally spaced dates, by type and layer."""
    dates = elements.agg(F.min("born").alias("lo"), F.max("born").alias("hi"))
    days = dates.select("lo", F.explode(F.sequence(F.lit(0), F.lit(times - 1))).alias("day"), F.datediff("hi", "lo").alias("range"))
    days = days.select("day", F.expr(f"date_add(lo, int(range * (day + 1) div {times}))").alias("until"))
    layer = F.floor(F.col("z") / 2000.0 + 0.5).cast("bigint")
    alive = elements.withColumn("layer", layer).join(F.broadcast(days), F.col("born") <= F.col("until"))
    return alive.groupBy("day", "cell_type", "layer").agg(F.count(F.lit(1)).alias("n_elements"), F.countDistinct("cell_id").alias("n_cells"))
