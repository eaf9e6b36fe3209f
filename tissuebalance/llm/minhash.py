"""Near-duplicate documents: SuperMinHash signatures, banding, exact verification, components.

* A SuperMinHash signature draws, for each element, one random permutation of the signature's
  places and gives the place at position j the value j + u, u uniform. Values of one element
  are correlated, which lowers the variance; once every place holds a value below j, deeper
  positions cannot matter and the element stops early.
* Documents with the same set are one class and only its smallest id goes on, so exact copies
  never meet again. With four rows to a band and 32 bands a pair of similarity 0.8 shares no
  band with probability below 1e-7.
* Links: each document is held against the smallest member of its buckets. Where a bucket's
  documents of similar size are still in several components, those outside the largest one are
  held against all of them, in blocks. So every pair that shares a bucket is compared, unless it
  is linked already or its sizes alone rule the similarity out.
* Groups: tasks join their own edges by union-find; what is left between tasks is a graph of
  their roots, which goes through again. Roots are chosen by a hash of their ids, so that chains
  of rising ids shrink as fast as any other graph.
* Classes and hubs that hold more than a small share of the rows are few, so they are joined by
  broadcast or dealt over parts; everything else is joined by its key.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Workspace, batch, chunks, mix64, sliced
from .shingles import shingle_sets


#: Documents with the same set.
CLASS = ("n_shingles", "key_a", "key_b")


@dataclass(frozen=True)
class Settings:
    words: int = 5
    percent: int = 80
    bands: int = 32
    rows: int = 4
    piece: int = 1 << 20


def superminhash(sets: list[np.ndarray], places: int) -> np.ndarray:
    """One row of `places` values (position << 32 | random bits) for each set; empty sets keep the largest value."""
    n = np.array([len(s) for s in sets], np.int64)
    values = np.full(len(sets) * places, np.iinfo(np.uint64).max, np.uint64)
    elements = np.concatenate(sets) if len(sets) else np.empty(0, np.uint64)
    owner = np.repeat(np.arange(len(sets)), n)
    shuffled = np.tile(np.arange(places, dtype=np.uint8 if places <= 256 else np.uint16), (len(elements), 1))
    live = np.arange(len(elements))
    with np.errstate(over="ignore"):
        for j in range(places):
            if not len(live):
                break
            draw = mix64(elements[live] + np.uint64((j + 1) * 0x9E3779B97F4A7C15 & (1 << 64) - 1))
            pick = j + ((draw >> np.uint64(32)) * np.uint64(places - j) >> np.uint64(32)).astype(np.int64)
            place = shuffled[live, pick].astype(np.int64)
            shuffled[live, pick] = shuffled[live, j]
            np.minimum.at(values, owner[live] * places + place, np.uint64(j << 32) | (draw & np.uint64(0xFFFFFFFF)))
            open_ = values.reshape(len(sets), places).max(axis=1) >= np.uint64((j + 1) << 32)
            live = live[open_[owner[live]]]
    return values.reshape(len(sets), places)


def band_keys(signatures: np.ndarray, bands: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        parts = signatures.reshape(len(signatures), bands, -1)
        h = np.broadcast_to(np.arange(1, bands + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15), parts.shape[:2]).copy()
        for r in range(parts.shape[2]):
            h = mix64((h ^ parts[:, :, r]) * np.uint64(0xE7037ED1A0B428DB))
        return h.view(np.int64)


def signed(docs: DataFrame, s: Settings) -> DataFrame:
    """doc_id, size of the set, two hashes of it and its band keys."""
    schema = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("key_a", pa.int64()), ("key_b", pa.int64()), ("bands", pa.list_(pa.int64()))])

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for got in sliced(it):
            ids, texts = got.column(0), got.column(1).to_pylist()
            for a, b in chunks(texts, s.piece):
                sets = shingle_sets(texts[a:b], s.words)
                keys = band_keys(superminhash(sets, s.bands * s.rows), s.bands)
                with np.errstate(over="ignore"):
                    key_a = [int(x.sum(dtype=np.uint64).view(np.int64)) for x in sets]
                    key_b = [int(mix64(x).sum(dtype=np.uint64).view(np.int64)) for x in sets]
                flat = pa.ListArray.from_arrays(pa.array(np.arange(b - a + 1, dtype=np.int32) * s.bands), pa.array(keys.ravel()))
                yield batch(schema, ids.slice(a, b - a), [len(x) for x in sets], key_a, key_b, flat)

    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    return rows.mapInArrow(run, "doc_id bigint, n_shingles bigint, key_a bigint, key_b bigint, bands array<bigint>")


def sets_of(docs: DataFrame, wanted: DataFrame, s: Settings) -> DataFrame:
    """The full sets of the documents whose ids are wanted, as sorted 64-bit hashes."""
    schema = pa.schema([("node", pa.int64()), ("hashes", pa.binary())])

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for got in sliced(it):
            texts = got.column(1).to_pylist()
            for a, b in chunks(texts, s.piece):
                yield batch(schema, got.column(0).slice(a, b - a), [x.tobytes() for x in shingle_sets(texts[a:b], s.words)])

    rows = docs.select(F.col("doc_id").cast("bigint").alias("node"), "text").where(F.col("text").isNotNull()).join(wanted, "node", "left_semi")
    return rows.mapInArrow(run, "node bigint, hashes binary")


def linked(pairs: DataFrame, sets: DataFrame, s: Settings) -> DataFrame:
    """The pairs (a, b) whose full sets reach the similarity."""
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])
    percent = s.percent

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for got in sliced(it):
            keep = []
            for x, y in zip(got.column("hashes_a"), got.column("hashes_b"), strict=True):
                u, v = (np.frombuffer(z.as_buffer(), np.uint64) for z in (x, y))
                if len(u) > len(v):
                    u, v = v, u
                at = np.searchsorted(v, u)
                at[at == len(v)] = 0
                both = int((v[at] == u).sum()) if len(v) else 0
                keep.append(100 * both >= percent * (len(u) + len(v) - both))
            yield batch(schema, got.column("a"), got.column("b")).filter(pa.array(keep, pa.bool_()))

    limit = hot_limit(pairs.count())
    hubs = pairs.groupBy("b").agg(F.ceil(F.count(F.lit(1)) / limit).alias("parts")).where("parts > 1").withColumnRenamed("b", "hub")
    of_a, of_b = (sets.select(F.col("node").alias(x), F.col("hashes").alias(f"hashes_{x}")) for x in "ab")
    dealt = pairs.join(F.broadcast(hubs), F.col("b") == F.col("hub"), "left").select("a", "b", F.coalesce(F.pmod(F.xxhash64("a"), "parts"), F.lit(0).cast("bigint")).alias("part"))
    of_b = of_b.join(F.broadcast(hubs), F.col("b") == F.col("hub"), "left").select("b", "hashes_b", F.explode(F.sequence(F.lit(0).cast("bigint"), F.coalesce("parts", F.lit(1).cast("bigint")) - 1)).alias("part"))
    held = dealt.join(of_a, "a").join(of_b, ["b", "part"])
    return held.select("a", "b", "hashes_a", "hashes_b").mapInArrow(run, "a bigint, b bigint")


def hot_limit(rows: int) -> int:
    """Rows that make a key hot: a thousandth of all, so that at most a thousand keys are; never more than a task holds with ease."""
    return min(max(1000, rows // 1000), 1_000_000)


FOREST = "node bigint, component bigint, order bigint, least bigint"


def union_find(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """For each node over the edges (a, b) of one task: the reachable node that comes first in the order of hashed ids,
    its place in that order, and the smallest reachable id."""
    parent: dict[int, int] = {}
    order: dict[int, int] = {}

    def root(x: int) -> int:
        top = x
        while parent[top] != top:
            top = parent[top]
        while parent[x] != top:
            parent[x], x = top, parent[x]
        return top

    for got in it:
        for name in ("a", "b"):
            ids = got.column(name).to_numpy()
            for x, h in zip(ids.tolist(), mix64(ids.view(np.uint64)).view(np.int64).tolist(), strict=True):
                parent.setdefault(x, x)
                order[x] = h
        for x, y in zip(got.column("a").to_pylist(), got.column("b").to_pylist(), strict=True):
            x, y = root(x), root(y)
            if x != y:
                x, y = (x, y) if order[x] < order[y] else (y, x)
                parent[y] = x
    least: dict[int, int] = {}
    for x in parent:
        top = root(x)
        least[top] = min(least.get(top, x), x)
    nodes = list(parent)
    schema = pa.schema([(n, pa.int64()) for n in ("node", "component", "order", "least")])
    for k in range(0, len(nodes), 10_000):
        part = nodes[k : k + 10_000]
        tops = [root(x) for x in part]
        yield batch(schema, part, tops, [order[x] for x in tops], [least[x] for x in tops])


def contracted(edges: DataFrame, space: Workspace, per_task: int) -> DataFrame:
    """node, component (some member of it), least (its smallest id)."""
    tasks = -(-edges.count() // per_task)
    local = edges.repartition(max(1, tasks)).mapInArrow(union_find, FOREST)
    if tasks <= 1:
        return local.select("node", "component", "least")
    local = space.write(local, "local")
    low = space.write(local.groupBy("node").agg(F.min(F.struct("order", "component")).getField("component").alias("low"), F.min("least").alias("least")), "low")
    above = low.select(F.col("node").alias("component"), F.col("low").alias("above"))
    links = local.join(low.select("node", "low"), "node").join(above, "component").select(F.col("above").alias("a"), F.col("low").alias("b")).where("a <> b").distinct()
    roots = contracted(space.write(links, "roots"), space, per_task).select(F.col("node").alias("low"), F.col("component").alias("root"))
    own = low.groupBy("low").agg(F.min("least").alias("own")).join(roots, "low", "left").withColumn("root", F.coalesce("root", "low"))
    own = space.write(own, "own")
    whole = own.join(own.groupBy("root").agg(F.min("own").alias("whole")), "root").select("low", "root", "whole")
    return low.join(whole, "low").select("node", F.col("root").alias("component"), F.col("whole").alias("least"))


def components(edges: DataFrame, space: Workspace, per_task: int = 200_000) -> DataFrame:
    """node, component (smallest reachable id) for every node of the edges (a, b), an edge table in the workspace.

    Tasks of at most about per_task edges contract their own; where there are several, the roots
    that they gave to one node are linked and the smaller graph of roots goes through again.
    """
    return contracted(edges, space, per_task).select("node", F.col("least").alias("component"))


def near_duplicates(docs: DataFrame, s: Settings = Settings()) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row of docs (doc_id, text).

    component_id is the smallest doc_id reachable over links (similarity of the sets of s.words-word
    shingles of at least s.percent hundredths); kept says that it is the row's own id. Texts that
    are null, empty or without words have an empty set and no links. Rows that share a doc_id count
    as one document; a row without doc_id is linked with nothing and kept. Extra columns are ignored.
    """
    space = Workspace(docs.sparkSession, "minhash")
    signs = space.write(signed(docs, s), "signed")
    own = signs.where("n_shingles > 0 and doc_id is not null")
    classes = own.groupBy(*CLASS).agg(F.min("doc_id").alias("node"), F.min(F.struct("doc_id", "bands")).getField("bands").alias("bands"), F.count(F.lit(1)).alias("n"))
    keyed = classes.select("node", "n_shingles", F.explode("bands").alias("bucket"))
    shared = keyed.groupBy("bucket").agg(F.min("node").alias("first"), F.max("node").alias("last")).where("first < last")
    members = space.write(keyed.join(shared.select("bucket", "first"), "bucket"), "members")
    size_fits = F.expr(f"100 * least(n_a, n_b) >= {s.percent} * greatest(n_a, n_b)")
    sizes = members.select("node", "n_shingles").distinct()

    def fit(pairs: DataFrame) -> DataFrame:
        n_a, n_b = (sizes.select(F.col("node").alias(x), F.col("n_shingles").alias(f"n_{x}")) for x in "ab")
        return pairs.join(n_a, "a").join(n_b, "b").where(size_fits)

    stars = space.write(fit(members.where("node <> first").select(F.col("node").alias("a"), F.col("first").alias("b")).distinct()).select("a", "b"), "stars")
    sets = space.write(sets_of(docs, members.select("node").distinct(), s), "sets")
    edges = space.write(linked(stars, sets, s), "links")
    found = space.write(components(edges, space), "components")
    late = space.write(links_in_buckets(members, found, sets, s), "late")
    if not late.isEmpty():
        found = space.write(components(space.write(edges.union(late), "links"), space), "components")
    grouped = classes.select(*(F.col(c).alias(f"_{c}") for c in CLASS), "node", "n").join(found, "node", "left").where("n > 1 or component is not null")
    grouped = space.write(grouped.select(*(f"_{c}" for c in CLASS), "n", F.coalesce("component", "node").alias("group")), "groups")
    limit = hot_limit(signs.count())
    same = " and ".join(f"{c} = _{c}" for c in CLASS)
    own_class = [f"_{c}" for c in CLASS]
    rows = signs.select("doc_id", *CLASS).join(F.broadcast(grouped.where(F.col("n") > limit).drop("n")), F.expr(f"{same} and doc_id is not null"), "left").drop(*own_class)
    settled = F.col("group").isNotNull() | (F.col("n_shingles") == 0) | F.col("doc_id").isNull()
    rest = rows.where(~settled).drop("group").join(grouped.where(F.col("n") <= limit).drop("n"), F.expr(same), "left").drop(*own_class)
    rows = rows.where(settled).unionByName(rest).withColumn("group", F.coalesce("group", "doc_id"))
    return rows.select("doc_id", "n_shingles", F.col("group").alias("component_id"), F.coalesce(F.col("doc_id") == F.col("group"), F.lit(True)).alias("kept"))


def parity_bits(hashes: np.ndarray, owner: np.ndarray, n: int) -> np.ndarray:
    """1024 bits a set: how often its hashes meet each place, modulo 2. Two sets differ in at least as many elements as bits."""
    at = owner * 1024 + (hashes & np.uint64(1023)).astype(np.int64)
    odd = (np.bincount(at, minlength=n * 1024) & 1).astype(bool)
    return np.packbits(odd.reshape(n, 1024), axis=1).view(np.uint64)


def links_in_buckets(members: DataFrame, found: DataFrame, sets: DataFrame, s: Settings, block: int = 512) -> DataFrame:
    """Links (a, b) between components that share a bucket; members: node, n_shingles, bucket, first.

    A bucket is split into cells of two neighbouring size bands, so that any two sizes which the
    similarity allows meet in one. Those outside a cell's largest component are held against the
    whole cell, in blocks of about `block` nodes, so a task's size does not depend on the cell's.
    Cells with the same nodes count once. One link to each other component is enough. Pairs with
    the bucket's first node have been verified before.
    """
    band = F.floor(F.log("n_shingles") * ((1 - 1e-9) / max(np.log(100 / s.percent), 1e-3)))
    own = members.distinct().join(found, "node", "left").withColumn("cell", F.explode(F.array(band - 1, band)))
    own = own.select("bucket", "cell", "first", "node", F.coalesce("component", "node").alias("component"))
    marks = [F.bit_xor(F.xxhash64("node", F.lit(k))).alias(f"mark_{k}") for k in (1, 2)]
    parts = own.groupBy("bucket", "cell", "component").agg(F.count(F.lit(1)).alias("n"), F.min("node").alias("low"), F.min("first").alias("first"), *marks)
    cells = parts.groupBy("bucket", "cell").agg(
        F.count(F.lit(1)).alias("parts"), F.sum("n").alias("all"), F.max("n").alias("most"), F.max_by("component", F.struct("n", F.negative("component"))).alias("largest"),
        F.min("low").alias("low"), F.min("first").alias("first"), *(F.bit_xor(f"mark_{k}").alias(f"mark_{k}") for k in (1, 2)),
    )
    mixed = cells.where("parts > 1 and (all > 2 or low <> first)").groupBy("all", "low", "mark_1", "mark_2").agg(F.min(F.struct("bucket", "cell", "most", "largest")).alias("one"))
    here = own.drop("first").join(mixed.select("all", "one.*"), ["bucket", "cell"])
    wide, deep = F.ceil(F.col("all") / block), F.ceil((F.col("all") - F.col("most")) / block)
    at = F.xxhash64("node", F.lit(s.words))
    few = here.where("component <> largest").withColumn("j", F.pmod(at, deep)).withColumn("i", F.explode(F.sequence(F.lit(0).cast("bigint"), wide - 1)))
    every = here.withColumn("i", F.pmod(at, wide)).withColumn("j", F.explode(F.sequence(F.lit(0).cast("bigint"), deep - 1)))
    columns = ["bucket", "cell", "i", "j", "node", "component", "hashes"]
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def opened(side: pa.Table) -> tuple[list[np.ndarray], np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Sets from the smallest, their sizes, bits, nodes and components."""
        blobs = [np.frombuffer(h.as_buffer(), np.uint64) for h in side.column("hashes")]
        size = np.array([len(x) for x in blobs])
        order = np.argsort(size, kind="stable")
        blobs, size = [blobs[k] for k in order], size[order]
        bits = parity_bits(np.concatenate(blobs), np.repeat(np.arange(len(blobs)), size), len(blobs))
        return blobs, size, bits, side.column("node").to_numpy()[order], side.column("component").to_numpy()[order]

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        out: list[tuple[int, int]] = []
        if left.num_rows and right.num_rows:
            mine, n_mine, bits_mine, ids_mine, groups_mine = opened(left)
            theirs, n_theirs, bits_theirs, ids_theirs, groups_theirs = opened(right)
            _, group = np.unique(np.concatenate([groups_mine, groups_theirs]), return_inverse=True)
            low, high = np.searchsorted(n_theirs, -(-s.percent * n_mine // 100)), np.searchsorted(n_theirs, 100 * n_mine // s.percent, "right")
            for k, x in enumerate(mine):
                near = slice(low[k], high[k])
                differ = np.bitwise_count(bits_theirs[near] ^ bits_mine[k]).sum(axis=1, dtype=np.int64)
                total = n_theirs[near] + len(x)
                able = ((100 + s.percent) * differ <= (100 - s.percent) * total) & (group[len(mine) :][near] != group[k])
                for r in (np.flatnonzero(able) + low[k]).tolist():
                    if group[len(mine) + r] != group[k]:
                        both = len(np.intersect1d(x, theirs[r], assume_unique=True))
                        if 100 * both >= s.percent * (len(x) + len(theirs[r]) - both):
                            out.append((max(int(ids_mine[k]), int(ids_theirs[r])), min(int(ids_mine[k]), int(ids_theirs[r]))))
                            group[group == group[len(mine) + r]] = group[k]
        return pa.table([pa.array([o[k] for o in out], pa.int64()) for k in (0, 1)], schema=schema)

    few, every = (side.join(sets, "node").select(*(F.col(c).alias(c) for c in columns)) for side in (few, every))
    pairs = few.groupBy("bucket", "cell", "i", "j").cogroup(every.groupBy("bucket", "cell", "i", "j"))
    return pairs.applyInArrow(run, "a bigint, b bigint").distinct()
