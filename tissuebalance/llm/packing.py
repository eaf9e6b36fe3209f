"""Packing token sequences by non-negative least squares.

Every document is cut into full windows and one rest shorter than a window. The histogram of
rests (one bin for each length, whatever the corpus holds) is matched by shallow combinations
of lengths that fill a window: pairs, triples of frequent lengths and lone powers of two.
Repeat counts solve a non-negative least-squares problem and are rounded down so that no
length is used more often than it occurs; rests that are left over are packed greedily, end to
end, cut where a window is full, and the last partial window is cut into powers of two.

A rest's place follows from its rank among rests of its length by arithmetic alone, so no task
ever gathers them. Ranks come from counts by task and length and a running sum over tasks.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import Workspace, batch, sliced

#: Sequence ids of full windows start here; planned and residual sequences stay below.
FULL = 1 << 40
TASK = 1 << 36


@dataclass(frozen=True)
class Plan:
    """slots[length]: ascending (first rank, first sequence, offset) of the patterns' uses of that length."""

    window: int
    slots: dict[int, list[tuple[int, int, int]]]
    used: np.ndarray
    residual_at: np.ndarray
    residual_sequence: int
    residual_tokens: int


def candidates(histogram: np.ndarray, window: int, frequent: int = 40) -> list[tuple[int, ...]]:
    """Multisets of at most three lengths that need no padding."""
    present = np.flatnonzero(histogram).tolist()
    held = set(present)
    out = [(a, window - a) for a in present if 2 * a <= window and window - a in held]
    out += [(1 << k,) for k in range(window.bit_length() - 1) if 1 << k in held]
    top = sorted(present, key=lambda n: (-histogram[n], n))[:frequent]
    out += sorted({tuple(sorted((a, b, window - a - b))) for a in top for b in top if a <= b and window - a - b in held})
    return out


def solve(histogram: np.ndarray, patterns: list[tuple[int, ...]], sweeps: int = 60) -> np.ndarray:
    """min |A x - h|, x >= 0, by cyclic coordinate descent; A counts each length in each pattern."""
    rest = histogram.astype(float)
    x = np.zeros(len(patterns))
    columns = [np.unique(p, return_counts=True) for p in patterns]
    for _ in range(sweeps):
        moved = 0.0
        for k, (at, n) in enumerate(columns):
            step = max(-x[k], float(rest[at] @ n) / float(n @ n))
            x[k] += step
            rest[at] -= step * n
            moved = max(moved, abs(step))
        if moved < 0.25:
            break
    return x


def plan(histogram: np.ndarray, window: int) -> Plan:
    """histogram[n]: how many rests have length n, 0 <= n < window."""
    left = histogram.astype(np.int64).copy()
    left[0] = 0
    patterns = candidates(left, window)
    repeats = np.floor(solve(left, patterns) + 1e-9).astype(np.int64)
    slots: dict[int, list[tuple[int, int, int]]] = {}
    used, sequence = np.zeros(window, np.int64), 0
    for k in np.argsort(-repeats, kind="stable").tolist():
        lengths = patterns[k]
        at, n = np.unique(lengths, return_counts=True)
        times = int(min(repeats[k], (left[at] // n).min()))
        if times <= 0:
            continue
        offset = 0
        for length in lengths:
            slots.setdefault(length, []).append((int(used[length]), sequence, offset))
            used[length] += times
            offset += length
        left[at] -= times * n
        sequence += times
    sizes = left * np.arange(window)
    return Plan(window, slots, used, np.cumsum(sizes) - sizes, sequence, int(sizes.sum()))


def place_rest(p: Plan, length: int, rank: int) -> list[tuple[int, int, int, int]]:
    """(start in the rest, length, sequence, offset) of the pieces of one rest."""
    if rank < p.used[length]:
        found = p.slots[length]
        lo, hi = 0, len(found)
        while hi - lo > 1:
            mid = (lo + hi) // 2
            lo, hi = (mid, hi) if found[mid][0] <= rank else (lo, mid)
        first, sequence, offset = found[lo]
        return [(0, length, sequence + rank - first, offset)]
    out, at = [], int(p.residual_at[length]) + (rank - int(p.used[length])) * length
    whole = p.residual_tokens // p.window * p.window
    done = 0
    while done < length:
        here = at + done
        if here < whole:
            begin, size, sequence = here // p.window * p.window, p.window, p.residual_sequence + here // p.window
        else:  # the last partial window, in powers of two, largest first
            begin, rest, sequence = whole, p.residual_tokens - whole, p.residual_sequence + whole // p.window
            size = 1 << rest.bit_length() - 1
            while here >= begin + size:
                begin, rest, sequence = begin + size, rest - size, sequence + 1
                size = 1 << rest.bit_length() - 1
        n = min(length - done, begin + size - here)
        out.append((done, n, sequence, here - begin))
        done += n
    return out


ENCODED = "doc_id bigint, task int, rest int, rank bigint, full_before bigint, doc_tokens bigint, ids binary"
PIECES = "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, sequence_id bigint, offset bigint"
ENCODED_ARROW = pa.schema([("doc_id", pa.int64()), ("task", pa.int32()), ("rest", pa.int32()), ("rank", pa.int64()), ("full_before", pa.int64()), ("doc_tokens", pa.int64()), ("ids", pa.binary())])
PIECES_ARROW = pa.schema([(n, pa.int64()) for n in ("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")])


def encoded(it: Iterator[pa.RecordBatch], encoder, window: int) -> Iterator[pa.RecordBatch]:
    task = TaskContext.get().partitionId()
    ranks, full = [0] * window, 0
    for got in sliced(it):
        columns: list[list] = [[] for _ in range(5)]
        blobs = []
        for ids in encoder().encode(got.column(1).to_pylist()):
            n = len(ids) + 1
            rest = n % window
            for c, v in zip(columns, (task, rest, ranks[rest], full, n), strict=True):
                c.append(v)
            ranks[rest] += 1
            full += n // window
            blobs.append(ids.astype("<u2").tobytes())
        yield batch(ENCODED_ARROW, got.column(0), *columns, blobs)


def pieces(it: Iterator[pa.RecordBatch], p: Plan) -> Iterator[pa.RecordBatch]:
    for got in sliced(it):
        out: list[tuple] = []
        rows = zip(*(got.column(n).to_pylist() for n in ("doc_id", "task", "rest", "rank", "full_before", "doc_tokens", "ids", "base")), strict=True)
        for doc, task, rest, rank, full, n, blob, base in rows:
            ids = np.append(np.frombuffer(blob, "<u2"), 0).astype("<u4")
            for k in range(n // p.window):
                part = ids[k * p.window : (k + 1) * p.window]
                out.append((doc, k * p.window, p.window, zlib.crc32(part.tobytes()), n, FULL + task * TASK + full + k, 0))
            if rest:
                for at, size, sequence, offset in place_rest(p, rest, base + rank):
                    part = ids[n - rest + at : n - rest + at + size]
                    out.append((doc, n - rest + at, size, zlib.crc32(part.tobytes()), n, sequence, offset))
        yield batch(PIECES_ARROW, *(zip(*out, strict=True) if out else [[]] * 7))


def pack(docs: DataFrame, encoder, window: int = 1024) -> DataFrame:
    """One row for each piece of every row of docs (doc_id, text); encoder() gives bpe.Encoder's interface.

    Each document's ids are followed by id 0, so empty and null texts are one token. Repeated
    rows are packed each on their own, extra columns are ignored, an empty table gives none.
    """
    spark = docs.sparkSession
    space = Workspace(spark, "packing")
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    kept = space.write(rows.mapInArrow(lambda it: encoded(it, encoder, window), ENCODED), "ids")
    counts = kept.groupBy("task", "rest").agg(F.count(F.lit(1)).alias("n"))
    histogram = np.zeros(window, np.int64)
    for r in counts.groupBy("rest").agg(F.sum("n").alias("n")).collect():  # at most `window` rows
        histogram[r.rest] = r.n
    how = spark.sparkContext.broadcast(plan(histogram, window))
    before = Window.partitionBy("rest").orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
    bases = counts.select("task", "rest", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    return kept.join(bases, ["task", "rest"]).mapInArrow(lambda it: pieces(it, how.value), PIECES)
