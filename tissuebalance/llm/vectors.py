"""Vectors as arrays in blocks, and the top rows of queries."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def usable(column: str = "embedding", zero: bool = False) -> Column:
    """Whether a vector is present, without null or non-finite parts and, unless zero, not all zero."""
    bad = F.exists(column, lambda x: x.isNull() | F.isnan(x) | (F.abs(x.cast("double")) == float("inf")))
    ok = F.col(column).isNotNull() & (F.size(column) > 0) & ~bad
    return F.coalesce(ok if zero else ok & F.exists(column, lambda x: x != 0), F.lit(False))


def regular(vectors: DataFrame) -> DataFrame:
    """Rows (vec_id, embedding) with an id and of the most frequent length (the longer of equals), one for each id: its smallest vector in array order."""
    known = vectors.where("vec_id is not null")
    size = known.groupBy(F.size("embedding").alias("size")).agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), F.desc("size")).first()
    if size is None:
        return known
    known = known.where(F.size("embedding") == size["size"])
    if known.groupBy("vec_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").isEmpty():
        return known
    return known.groupBy("vec_id").agg(F.min("embedding").alias("embedding"))


def stacked(column: pa.ChunkedArray | pa.Array) -> np.ndarray:
    """A list column as rows of doubles. All lists must have one length."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    n = len(column)
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(n, -1) if n else np.zeros((0, 0))


def exact(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Inner products of matching rows, added in one fixed order, so equal vectors score the same."""
    return (a * b).sum(axis=1)


def best_rows(scores: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Positions of the k largest scores, ties to smaller ids."""
    if len(scores) > k:
        edge = np.partition(scores, len(scores) - k)[len(scores) - k]
        some = np.flatnonzero(scores >= edge)
    else:
        some = np.arange(len(scores))
    return some[np.lexsort((ids[some], -scores[some]))][:k]


def ranked(hits: DataFrame, k: int) -> DataFrame:
    """query_id, rank, vec_id, score of the k best hits (query_id, vec_id, score) of each query."""
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return hits.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
