"""Exact top-k by inner product: pivot-table elimination.

Distances of every row to a fixed number of pivots are computed once. For a query, the largest
difference of distances to a pivot is a lower bound on its distance to the row, and so gives an
upper bound on their inner product. Rows of a block are evaluated in the order of that bound
until the bound falls below the k-th best score known; the rest cannot enter the result.

Rows are held by cells around far-apart points, and each cell keeps the range of its rows'
distances to every pivot, which bounds what a query can find in it. A pass over a bounded set of
rows gives each query a score that k rows reach; it goes only to cells whose bound comes up to
it, and cells that no query goes to are not shuffled. Large cells are dealt over blocks, and a
cell's many queries over groups.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from .common import Workspace, batch
from .vectors import ranked, regular, stacked

HITS = "query_id bigint, vec_id bigint, score bigint, tested bigint"
HITS_ARROW = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64()), ("tested", pa.int64())])


def distances(x: np.ndarray, pivots: np.ndarray) -> np.ndarray:
    square = (x**2).sum(axis=1)[:, None] + (pivots**2).sum(axis=1) - 2 * x @ pivots.T
    return np.sqrt(np.maximum(square, 0))


def top_of_block(q: np.ndarray, q_id: int, q_table: np.ndarray, x: np.ndarray, ids: np.ndarray, table: np.ndarray, norms: np.ndarray, k: int, least: float, step: int = 64) -> tuple[np.ndarray, np.ndarray, int]:
    """ids and scores of rows of a block that may be among the query's k best, and how many were evaluated; least: a score that k rows reach."""
    low = np.abs(table - q_table).max(axis=1)
    # A thousandth more than the rounding of distances can take away.
    bound = (float(q @ q) + norms - np.maximum(low - 1e-6 * (1 + low), 0) ** 2) / 2 + 1e-3
    order = np.argsort(-bound, kind="stable")
    order = order[ids[order] != q_id]
    got_ids, got = np.empty(0, np.int64), np.empty(0)
    a = 0
    while a < len(order) and bound[order[a]] >= least:
        part = order[a : a + step]
        score = x[part] @ q
        got_ids, got = np.concatenate([got_ids, ids[part]]), np.concatenate([got, score])
        top = np.lexsort((got_ids, -got))[:k]
        got_ids, got = got_ids[top], got[top]
        if len(got) == k:
            least = max(least, float(got[-1]))
        a, step = a + step, min(2 * step, 1024)
    return got_ids, got, min(a, len(order))


@dataclass
class Cells:
    """What a query has to know of the rows: for each cell the ranges of distances to the pivots, and the largest squared length."""

    number: np.ndarray
    low: np.ndarray
    high: np.ndarray
    norm: np.ndarray

    def reachable(self, square: float, table: np.ndarray, least: float) -> np.ndarray:
        """Cells that may hold a row whose inner product with the query is at least `least`."""
        apart = np.maximum(np.maximum(self.low - table, table - self.high), 0).max(axis=1)
        apart = np.maximum(apart - 1e-6 * (1 + self.high.max(axis=1) + table.max()), 0)
        bound = np.minimum((square + self.norm - apart**2) / 2, np.sqrt(square * self.norm))
        return self.number[bound + 1e-9 * np.abs(bound) + 1e-3 >= least]


def far_points(x: np.ndarray, n: int) -> np.ndarray:
    """Rows of which each is as far as possible from those before it."""
    chosen = [0]
    far = distances(x, x[[0]])[:, 0]
    while len(chosen) < min(n, len(x)) and far.max() > 0:
        chosen.append(int(far.argmax()))
        far = np.minimum(far, distances(x, x[[chosen[-1]]])[:, 0])
    return x[chosen]


ASKS = "query_id bigint, embedding array<double>, pivots array<double>, least double, cells array<bigint>"
ASKS_ARROW = pa.schema([("query_id", pa.int64()), ("embedding", pa.list_(pa.float64())), ("pivots", pa.list_(pa.float64())), ("least", pa.float64()), ("cells", pa.list_(pa.int64()))])
ROWS = "vec_id bigint, embedding array<double>, pivots array<double>, norm double, cell bigint"
ROWS_ARROW = pa.schema([("vec_id", pa.int64()), ("embedding", pa.list_(pa.float64())), ("pivots", pa.list_(pa.float64())), ("norm", pa.float64()), ("cell", pa.int64())])


def search(vectors: DataFrame, queries: DataFrame, k: int, n_pivots: int = 32, row_block: int = 4096, query_block: int = 2048, most_cells: int = 1024, observation: Observation | None = None) -> DataFrame:
    """query_id, rank, vec_id, score of the k rows with the highest integer inner products.

    vectors: vec_id, embedding (whole numbers as doubles, exact below 2**53 in sums); queries:
    query_id, embedding. Rows without an id and vectors that have not the most frequent length
    take no part; of rows that share an id the one with the smallest vector counts. Extra columns
    are ignored. Ties go to smaller ids; a query's own id is no candidate; fewer rows than k give
    them all; no rows or queries give none. Pivots, cells and first rows are at most n_pivots,
    most_cells and row_block, whatever the table's size. observation receives the number of inner
    products taken (`tested`).
    """
    spark = vectors.sparkSession
    space = Workspace(spark, "pivots")
    empty = spark.createDataFrame([], "query_id bigint, rank int, vec_id bigint, score bigint")
    vectors = regular(vectors.select("vec_id", "embedding"))
    first = vectors.orderBy(F.xxhash64("vec_id"), "vec_id").limit(row_block).toArrow()
    if not first.num_rows:
        return empty
    x, ids = stacked(first.column("embedding")), first.column("vec_id").to_numpy()
    queries = regular(queries.select(F.col("query_id").alias("vec_id"), "embedding")).where(F.size("embedding") == x.shape[1]).withColumnRenamed("vec_id", "query_id")
    total = vectors.count()
    points = far_points(x, max(n_pivots, min(most_cells, 4 * total // row_block)))
    shared = spark.sparkContext.broadcast((points, points[:n_pivots], x, ids))

    def placed(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        points, pivots, _, _ = shared.value
        for got in it:
            for part in (got.slice(a, 2048) for a in range(0, got.num_rows, 2048)):
                v = stacked(part.column(1))
                far = distances(v, points)
                yield batch(ROWS_ARROW, part.column(0), list(v), list(far[:, : len(pivots)]), (v**2).sum(axis=1), far.argmin(axis=1))

    rows = space.write(vectors.mapInArrow(placed, ROWS), "rows")
    n = min(n_pivots, len(points))
    ranges = [f(F.get("pivots", F.lit(i))).alias(f"{name}{i}") for name, f in (("low", F.min), ("high", F.max)) for i in range(n)]
    found = rows.groupBy("cell").agg(F.count(F.lit(1)).alias("n"), F.max("norm").alias("norm"), *ranges).collect()  # one row for each cell
    cells = spark.sparkContext.broadcast(Cells(np.array([r.cell for r in found]), *(np.array([[r[f"{name}{i}"] for i in range(n)] for r in found]) for name in ("low", "high")), np.array([r.norm for r in found])))

    def asked(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _, pivots, some, some_ids = shared.value
        for got in it:
            for part in (got.slice(a, 512) for a in range(0, got.num_rows, 512)):
                v, own = stacked(part.column(1)), part.column(0).to_numpy()
                far, least = distances(v, pivots), np.full(len(v), -np.inf)
                if len(some) > k:
                    s = v @ some.T
                    s[own[:, None] == some_ids] = -np.inf
                    least = np.partition(s, s.shape[1] - k, axis=1)[:, s.shape[1] - k]
                yield batch(ASKS_ARROW, part.column(0), list(v), list(far), least, [cells.value.reachable(float(q @ q), t, w) for q, t, w in zip(v, far, least, strict=True)])

    asks = space.write(queries.mapInArrow(asked, ASKS), "queries")
    visits = {r.cell: r.n for r in asks.select(F.explode("cells").alias("cell")).groupBy("cell").agg(F.count(F.lit(1)).alias("n")).collect()}
    shape = [(r.cell, -(-r.n // row_block), -(-visits[r.cell] // query_block)) for r in found if r.cell in visits]
    if not shape:
        return empty
    shape = F.broadcast(spark.createDataFrame(shape, "cell bigint, blocks bigint, groups bigint"))
    zero = F.lit(0).cast("bigint")
    left = asks.withColumn("cell", F.explode("cells")).join(shape, "cell").withColumns({"group": F.pmod(F.xxhash64("query_id"), "groups"), "block": F.explode(F.sequence(zero, F.col("blocks") - 1))})
    right = rows.join(shape, "cell").withColumns({"block": F.pmod(F.xxhash64("vec_id"), "blocks"), "group": F.explode(F.sequence(zero, F.col("groups") - 1))})

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        out: list[list[np.ndarray]] = [[], [], [], []]
        if left.num_rows and right.num_rows:
            v, table, own = stacked(right.column("embedding")), stacked(right.column("pivots")), right.column("vec_id").to_numpy()
            q, q_table, least = stacked(left.column("embedding")), stacked(left.column("pivots")), left.column("least").to_numpy()
            norms = right.column("norm").to_numpy()
            for i, q_id in enumerate(left.column("query_id").to_pylist()):
                got_ids, got, tested = top_of_block(q[i], q_id, q_table[i], v, own, table, norms, k, least[i])
                keep = got >= least[i]
                # The last row tells of the tests and is no hit.
                keep_ids, keep_scores = np.append(got_ids[keep], -1), np.append(got[keep], 0)
                counts = np.zeros(len(keep_ids), np.int64)
                counts[-1] = tested + 1
                for o, value in zip(out, (np.full(len(keep_ids), q_id), keep_ids, keep_scores.astype(np.int64), counts), strict=True):
                    o.append(value)
        return pa.table([pa.array(np.concatenate(o) if o else [], f.type) for o, f in zip(out, HITS_ARROW, strict=True)], schema=HITS_ARROW)

    keys = ("cell", "block", "group")
    left = left.select(*(F.col(c).alias(c) for c in (*keys, "query_id", "embedding", "pivots", "least"))).groupBy(*keys)
    right = right.select(*(F.col(c).alias(c) for c in (*keys, "vec_id", "embedding", "pivots", "norm"))).groupBy(*keys)
    hits = left.cogroup(right).applyInArrow(run, HITS)
    if observation:
        hits = hits.observe(observation, F.sum(F.when(F.col("tested") > 0, F.col("tested") - 1)).alias("tested"))
    return ranked(hits.where("tested = 0").drop("tested"), k)
