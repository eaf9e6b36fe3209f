"""Array kernels that tasks run on their own rank."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd

from ..functions import forces

PAIRS_AT_ONCE = 30_000


def expanded(starts: np.ndarray, sizes: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs (i, j) with j in the range of i, sizes[i] long from starts[i], in pieces of whole ranges."""
    upto = np.cumsum(sizes)
    if not len(upto) or not upto[-1]:
        return
    cuts = np.unique(np.searchsorted(upto, np.arange(0, upto[-1], PAIRS_AT_ONCE), "right"))
    for a, b in zip(cuts, [*cuts[1:], len(sizes)], strict=True):
        own = np.repeat(np.arange(a, b), sizes[a:b])
        before = upto[a:b] - sizes[a:b]
        yield own, np.arange(before[0], upto[b - 1]) + np.repeat(starts[a:b] - before, sizes[a:b])


class Around:
    """Rows of every about each of own: both in order of column by and of z, as rows of the two tables have no order.

    tests: the elements in the nine columns of bins around, of the planes that every has.
    """

    def __init__(self, own: pd.DataFrame, every: pd.DataFrame, cutoff: float) -> None:
        self.reach, self.most = int(cutoff // 1), cutoff * cutoff
        self.own, self.every = (df.iloc[np.lexsort((df["z"].to_numpy(), df["by"].to_numpy()))] for df in (own, every))
        self.mine, self.at = ([df[a].to_numpy(np.float64) for a in "xyz"] for df in (self.own, self.every))  # whole numbers below 2 ** 53
        self.n = self.every["n"].to_numpy(np.int64)
        total = np.concatenate([[0], np.cumsum(self.n)])
        self.tests, self.ranges = np.zeros(len(own), np.int64), []
        by = [df["by"].to_numpy(np.int64) - every["by"].min() for df in (self.own, self.every)]
        for name, reach in (("bz", 1), ("z", self.reach)):
            near, all_ = (df[name].to_numpy(np.int64) - every[name].min() for df in (self.own, self.every))
            span = int(all_.max()) + 2 * reach + 2
            keys = by[1] * span + all_
            for d in (-1, 0, 1):
                middle = (by[0] + d) * span + near
                low, high = np.searchsorted(keys, middle - reach, "left"), np.searchsorted(keys, middle + reach, "right")
                if name == "bz":
                    self.tests += total[high] - total[low]
                else:
                    self.ranges.append((low, high - low))

    def pairs(self) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """Rows i of own and j of every within the cutoff, each with itself too, and the squares of their distances."""
        for low, sizes in self.ranges:
            for i, j in expanded(low, sizes):
                square = sum((m[i] - o[j]) ** 2 for m, o in zip(self.mine, self.at, strict=True))
                met = np.flatnonzero(square <= self.most)
                yield i[met], j[met], square[met]


def count_kernel(cutoff: float) -> Callable:
    """Elements within the cutoff of one at each owned site, itself left out, and the elements in the bins around."""

    def run(own: pd.DataFrame, every: pd.DataFrame) -> pd.DataFrame:
        near, pairs = Around(own, every, cutoff), np.full(len(own), -1, np.int64)
        for i, j, _ in near.pairs():
            if len(i):
                first = i[0]  # i ascends, so a piece is a stretch of own
                got = np.bincount(i - first, near.n[j]).astype(np.int64)  # whole numbers below 2 ** 53
                pairs[first : first + len(got)] += got
        return near.own[["x", "y", "z", "n"]].assign(n_pairs=pairs, tests=near.tests)

    return run


def force_kernel(cutoff: float) -> Callable:
    """What the forces between cells give an element at each owned site, and the elements in the bins around."""

    def run(own: pd.DataFrame, every: pd.DataFrame) -> pd.DataFrame:
        near, v = Around(own, every, cutoff), np.zeros((len(own), 3))
        kinds = pd.factorize(pd.concat([near.own["cell_type"], near.every["cell_type"]], ignore_index=True))[0]
        own_kind, kind = kinds[: len(own)], kinds[len(own) :]
        for i, j, square in near.pairs():
            apart = square > 0
            i, j, r = i[apart], j[apart], np.sqrt(square[apart])
            if len(i):
                f = near.n[j] * forces.between_cells(r / cutoff, own_kind[i] == kind[j]) / r
                first = i[0]
                for k in range(3):
                    got = np.bincount(i - first, f * (near.mine[k][i] - near.at[k][j]))
                    v[first : first + len(got), k] += got
        return near.own[["x", "y", "z", "cell_type", "n"]].assign(vx=v[:, 0], vy=v[:, 1], vz=v[:, 2], tests=near.tests)

    return run


def cell_pushes(at: list[np.ndarray], kinds: np.ndarray, known: np.ndarray, starts: np.ndarray, sizes: np.ndarray, cutoff: float) -> np.ndarray:
    """What the forces of a row's own cell are more than those between cells would be, three columns.

    Rows of a cell stand together, sizes many from starts, both given for each row; those without a position (not known) push none.
    """
    u = np.zeros((len(kinds), 3))
    for i, j in expanded(starts, sizes):
        square = sum((p[i] - p[j]) ** 2 for p in at)
        met = np.flatnonzero((square > 0) & (square <= cutoff * cutoff) & known[i] & known[j])
        i, j, r = i[met], j[met], np.sqrt(square[met])
        if len(i):
            same = kinds[i] == kinds[j]
            f = (forces.within_cell(r / cutoff) - forces.between_cells(r / cutoff, same)) / r
            first = i[0]
            for k in range(3):
                got = np.bincount(i - first, f * (at[k][i] - at[k][j]))
                u[first : first + len(got), k] += got
    return u


def sweep_planes(parts: Iterator[pd.DataFrame], kernel: Callable) -> Iterator[pd.DataFrame]:
    """The kernel's rows for owned sites of each rank, with rank and seconds, over rows sorted by rank, run and plane.

    A plane is handed over with its two neighbours, so that three planes are held at a time.
    """
    held: list[tuple[tuple[int, int, int], pd.DataFrame]] = []

    def answer(middle: int) -> pd.DataFrame | None:
        (rank, run, plane), rows = held[middle]
        own = rows[~rows["is_ghost"]].reset_index(drop=True)
        if own.empty:
            return None
        begin = time.perf_counter()
        every = pd.concat([r for (*k, p), r in held if k == [rank, run] and abs(p - plane) <= 1], ignore_index=True)
        out = kernel(own, every)
        return out.assign(rank=np.int32(rank), seconds=(time.perf_counter() - begin) / len(own))

    def whole_planes() -> Iterator[tuple[tuple[int, int, int], pd.DataFrame]]:
        open_key, pieces = None, []
        for part in parts:
            for key, rows in part.groupby(["rank", "run", "bx"], sort=True):
                if key != open_key and pieces:
                    yield open_key, pd.concat(pieces, ignore_index=True)
                    pieces = []
                open_key = key
                pieces.append(rows)
        if pieces:
            yield open_key, pd.concat(pieces, ignore_index=True)

    for plane in whole_planes():
        held.append(plane)
        if len(held) > 1 and (got := answer(len(held) - 2)) is not None:
            yield got
        held = held[-2:]
    if held and (got := answer(len(held) - 1)) is not None:
        yield got
