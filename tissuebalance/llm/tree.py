"""Approximate nearest neighbours: a hierarchical k-means tree searched best bin first.

The tree is fitted on a bounded sample; every row is then stored under its leaf, and leaves
that hold more than a block are dealt over several blocks by a hash of the row's id. A query
visits leaves in the order of a priority queue over tree nodes, keyed by the inner product
with the node's centre plus the node's radius times the query's length. How many leaves it
visits is widened, on sample queries held against all rows, until their recall reaches the target.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Workspace, batch
from .vectors import best_rows, exact, ranked, regular, stacked


@dataclass(frozen=True)
class Settings:
    sample: int = 20_000
    branches: int = 8
    leaf: int = 64
    block: int = 4096
    recall: float = 0.97
    probes: int = 64
    rounds: int = 8


@dataclass
class Tree:
    centre: np.ndarray
    radius: np.ndarray
    first: np.ndarray
    children: np.ndarray
    leaf_of: np.ndarray
    n_leaves: int


def k_means(x: np.ndarray, k: int, rounds: int, rng: np.random.Generator) -> np.ndarray:
    """The cluster of each row; far starting points, then Lloyd's rounds."""
    centre = x[[rng.integers(len(x))]]
    far = ((x - centre[0]) ** 2).sum(axis=1)
    while len(centre) < k and far.max() > 0:
        centre = np.vstack([centre, x[rng.choice(len(x), p=far / far.sum())]])
        far = np.minimum(far, ((x - centre[-1]) ** 2).sum(axis=1))
    for _ in range(rounds):
        own = (x @ centre.T - (centre**2).sum(axis=1) / 2).argmax(axis=1)
        for c in range(len(centre)):
            if (own == c).any():
                centre[c] = x[own == c].mean(axis=0)
    return (x @ centre.T - (centre**2).sum(axis=1) / 2).argmax(axis=1)


def fit(x: np.ndarray, s: Settings) -> Tree:
    """Nodes in breadth-first order; node i's children are first[i] .. first[i] + children[i]."""
    rng = np.random.default_rng(7)
    centre, radius, first, children, leaf_of, rows = [], [], [], [], [], [np.arange(len(x))]
    k = 0
    n_leaves = 0
    while k < len(rows):
        own = x[rows[k]]
        centre.append(own.mean(axis=0))
        spread = np.sqrt(((own - centre[-1]) ** 2).sum(axis=1))
        radius.append(float(np.quantile(spread, 0.9)))
        group = k_means(own, s.branches, s.rounds, rng) if len(own) > s.leaf and spread.max() > 0 else np.zeros(len(own), int)
        first.append(len(rows))
        names = np.unique(group)
        if len(names) > 1:
            children.append(len(names))
            leaf_of.append(-1)
            rows += [rows[k][group == g] for g in names]
        else:
            children.append(0)
            leaf_of.append(n_leaves)
            n_leaves += 1
        rows[k] = rows[k][:0] if len(names) > 1 else rows[k]
        k += 1
    return Tree(np.array(centre), np.array(radius), np.array(first), np.array(children), np.array(leaf_of), n_leaves)


def assign(tree: Tree, x: np.ndarray) -> np.ndarray:
    """The leaf of each row: down the tree to the nearest centre."""
    node = np.zeros(len(x), np.int64)
    while True:
        inner = np.flatnonzero(tree.children[node] > 0)
        if not len(inner):
            return tree.leaf_of[node]
        for parent in np.unique(node[inner]):
            at = inner[node[inner] == parent]
            below = slice(tree.first[parent], tree.first[parent] + tree.children[parent])
            c = tree.centre[below]
            node[at] = tree.first[parent] + (x[at] @ c.T - (c**2).sum(axis=1) / 2).argmax(axis=1)


def visits(tree: Tree, q: np.ndarray, most: int, sizes: np.ndarray | None = None, rows: int = 0) -> list[int]:
    """The first leaves in best-bin-first order: `most`, or more until they hold that many rows."""
    length = float(np.sqrt(q @ q))
    queue, out, held = [(0.0, 0)], [], 0
    while queue and (len(out) < most or held < rows):
        _, node = heapq.heappop(queue)
        if tree.children[node]:
            a, b = tree.first[node], tree.first[node] + tree.children[node]
            bound = tree.centre[a:b] @ q + tree.radius[a:b] * length * 0.3
            for k, v in enumerate(bound.tolist()):
                heapq.heappush(queue, (-v, int(a) + k))
        else:
            out.append(int(tree.leaf_of[node]))
            held += int(sizes[out[-1]]) if sizes is not None else rows
    return out


def block_hits(queries: pa.Table, rows: pa.Table, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The k best rows of one block for each query, exactly scored."""
    q, x = stacked(queries.column("embedding")), stacked(rows.column("embedding"))
    q_ids, ids = queries.column("query_id").to_numpy(), rows.column("vec_id").to_numpy()
    rough = q @ x.T
    out: list[list[np.ndarray]] = [[], [], []]
    for i in range(len(q)):
        s = np.where(ids == q_ids[i], -np.inf, rough[i])
        if len(s) > k:
            edge = np.partition(s, len(s) - k)[len(s) - k]
            some = np.flatnonzero(s >= edge - 1e-9 * (1 + abs(edge)))
        else:
            some = np.flatnonzero(s > -np.inf)
        some = some[ids[some] != q_ids[i]]
        score = exact(np.broadcast_to(q[i], (len(some), q.shape[1])), x[some])
        top = best_rows(score, ids[some], k)
        out[0].append(np.full(len(top), q_ids[i]))
        out[1].append(ids[some[top]])
        out[2].append(score[top])
    return tuple(np.concatenate(o) if o else np.empty(0) for o in out)


HITS = "query_id bigint, vec_id bigint, score double"
HITS_ARROW = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.float64())])


def search(vectors: DataFrame, queries: DataFrame, k: int, s: Settings = Settings()) -> DataFrame:
    """query_id, rank, vec_id, score of each query's k nearest found rows by inner product.

    vectors: vec_id, embedding; queries: query_id, embedding. Rows without an id and vectors that
    have not the most frequent length take no part; of rows that share an id the one with the
    smallest vector counts. Extra columns are ignored. A query's own id is no candidate. With no
    rows or no queries the result is empty; with fewer rows than k it holds them all. The tree
    that tasks receive has at most about twice `sample` nodes.
    """
    spark = vectors.sparkSession
    vectors = regular(vectors.select("vec_id", "embedding"))
    queries = regular(queries.select(F.col("query_id").alias("vec_id"), "embedding")).withColumnRenamed("vec_id", "query_id")
    if not (width := vectors.select(F.size("embedding").alias("n")).first()) or queries.where(F.size("embedding") == width.n).isEmpty():
        return spark.createDataFrame([], "query_id bigint, rank int, vec_id bigint, score double")
    queries = queries.where(F.size("embedding") == width.n)
    space = Workspace(spark, "tree")
    total = vectors.count()
    unit = F.pmod(F.xxhash64("vec_id"), F.lit(1 << 30))
    some = vectors.where(unit < F.lit(int(min(1.0, s.sample / max(total, 1)) * (1 << 30)))).orderBy("vec_id").limit(2 * s.sample).select("embedding").toArrow()
    if not some.num_rows:
        some = vectors.orderBy("vec_id").limit(s.sample).select("embedding").toArrow()
    if not some.num_rows:
        return spark.createDataFrame([], "query_id bigint, rank int, vec_id bigint, score double")
    tree = spark.sparkContext.broadcast(fit(stacked(some.column(0)), s))
    leaves = tree.value.n_leaves

    def place(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for got in it:
            leaf = assign(tree.value, stacked(got.column(1))) if got.num_rows else []
            yield pa.RecordBatch.from_arrays([got.column(0), got.column(1), pa.array(leaf, pa.int64())], names=["vec_id", "embedding", "leaf"])

    stored = space.write(vectors.select("vec_id", "embedding").mapInArrow(place, f"vec_id bigint, embedding {vectors.schema['embedding'].dataType.simpleString()}, leaf bigint"), "rows")
    sizes = stored.groupBy("leaf").agg(F.count(F.lit(1)).alias("n")).withColumn("blocks", F.ceil(F.col("n") / s.block))
    rows_of = np.zeros(leaves, np.int64)
    for r in sizes.collect():  # one for each leaf
        rows_of[r.leaf] = r.n
    held = stored.join(F.broadcast(sizes.select("leaf", "blocks")), "leaf").withColumn("block", F.pmod(F.xxhash64("vec_id"), "blocks"))

    def asked(found: DataFrame, most: int) -> DataFrame:
        def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            schema = pa.schema([("query_id", pa.int64()), ("embedding", pa.list_(pa.float64())), ("leaf", pa.int64()), ("place", pa.int32())])
            for got in it:
                x = stacked(got.column(1)) if got.num_rows else np.zeros((0, 1))
                ids = got.column(0).to_pylist()
                for a in range(0, len(ids), 256):
                    lists = [visits(tree.value, v, most, rows_of, k + 1) for v in x[a : a + 256]]
                    rep = np.repeat(np.arange(len(lists)), [len(v) for v in lists])
                    yield batch(schema, np.array(ids[a : a + 256])[rep], list(x[a : a + 256][rep]), [v for one in lists for v in one], [p for one in lists for p in range(len(one))])

        return found.select("query_id", "embedding").mapInArrow(run, "query_id bigint, embedding array<double>, leaf bigint, place int")

    def hits(found: DataFrame, most: int, with_place: bool = False) -> DataFrame:
        wanted = asked(found, most).join(F.broadcast(sizes.select("leaf", "blocks")), "leaf").withColumn("block", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("blocks") - 1)))
        wanted = wanted.select(*(F.col(c).alias(c) for c in ("query_id", "embedding", "leaf", "block", "place")))

        def run(left: pa.Table, right: pa.Table) -> pa.Table:
            out = ([], [], []) if not left.num_rows or not right.num_rows else block_hits(left, right, k)
            return pa.table([pa.array(o, f.type) for o, f in zip(out, HITS_ARROW, strict=True)], schema=HITS_ARROW)

        rows = held.select(*(F.col(c).alias(c) for c in ("vec_id", "embedding", "leaf", "block")))
        return wanted.groupBy("leaf", "block").cogroup(rows.groupBy("leaf", "block")).applyInArrow(run, HITS)

    most = calibrate(tree.value, stored, queries, k, s, hits)
    return ranked(hits(queries, min(most, leaves)), k)


def calibrate(tree: Tree, stored: DataFrame, queries: DataFrame, k: int, s: Settings, hits) -> int:
    """The least number of visited leaves with which sample queries reach the recall, by exact search over all rows."""
    probes = queries.orderBy(F.xxhash64("query_id"), "query_id").limit(s.probes)
    every = ranked(hits(probes, tree.n_leaves), k)
    where = every.join(stored.select("vec_id", "leaf"), "vec_id").select("query_id", "leaf").collect()  # probes * k rows at most
    if not where:
        return 1
    asked = {r.query_id: stacked_one(r.embedding) for r in probes.select("query_id", "embedding").collect()}
    rank = {q: {leaf: p for p, leaf in enumerate(visits(tree, v, tree.n_leaves))} for q, v in asked.items()}
    places = sorted(rank[r.query_id][r.leaf] for r in where)
    return places[min(len(places) - 1, int(np.ceil(s.recall * len(places))) - 1)] + 1


def stacked_one(values) -> np.ndarray:
    return np.array(values, np.float64)
