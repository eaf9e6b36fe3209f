"""Suffix arrays by induced sorting, with array operations on whole stretches of buckets."""

from __future__ import annotations

import numpy as np

from .common import span_hashes

#: Up to this alphabet most buckets feed their neighbours, so looking ahead finds nothing.
SMALL_ALPHABET = 512


def spread(sizes: np.ndarray, begin: np.ndarray) -> np.ndarray:
    """begin[b], begin[b] + 1, ... (sizes[b] numbers) for each b, joined."""
    upto = np.cumsum(sizes)
    return np.arange(upto[-1]) + np.repeat(begin - (upto - sizes), sizes)


class Buckets:
    """Suffixes by first symbol; step says from which end of a bucket its free slots are taken.

    Slots that are still free hold suffix 0, which nothing precedes and so feeds no bucket.
    """

    def __init__(self, t: np.ndarray, feeds: np.ndarray, bounds: np.ndarray, free: np.ndarray, step: int) -> None:
        self.t, self.bounds, self.free, self.step = t, bounds.tolist(), free, step
        self.slots = np.zeros(self.bounds[-1], np.int32)
        self.ramp = np.arange(0, step * self.bounds[-1], step, np.int32)
        self.feeds = np.concatenate([[False], feeds[:-1]])  # by the type of what stands before

    def fed(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Which of the suffixes at feed a bucket, what stands before them, and its symbols."""
        hit = self.feeds[at].nonzero()[0]
        found = at[hit] - 1
        return hit, found, self.t[found]

    def push(self, found: np.ndarray, chars: np.ndarray) -> None:
        """Suffixes in the order of the scan go to their buckets' next free slots."""
        n = len(found)
        if not n:
            return
        if n > 1:
            order = chars.argsort(kind="stable")
            found, chars = found[order], chars[order]
        first = np.zeros(1, np.int64)
        if n > 1 and chars[0] != chars[-1]:
            first = np.concatenate((first, (chars[1:] != chars[:-1]).nonzero()[0] + 1))
        sizes = np.empty(len(first), np.int64)
        sizes[:-1] = first[1:] - first[:-1]
        sizes[-1] = n - first[-1]
        into = chars[first]
        base = self.free[into]
        self.slots[(base - self.step * first).repeat(sizes) + self.ramp[:n]] = found
        self.free[into] = base + self.step * sizes


def upwards(up: Buckets, n_large: list[int], k: int) -> None:
    """Fills in the larger types; a scan takes as many buckets at once as do not feed one another."""
    bounds, slots, free = up.bounds, up.slots, up.free
    c, look = 0, 1
    while c < k:
        m = c
        if k > SMALL_ALPHABET:
            end = min(k, c + look)
            hit, found, chars = up.fed(slots[bounds[c] : bounds[end]])
            inside = chars[chars < end]
            m = int(inside.min()) if len(inside) else end
            if m == end:
                up.push(found, chars)
            elif m > c:
                n = hit.searchsorted(bounds[m] - bounds[c])
                up.push(found[:n], chars[:n])
            look = 2 * (m - c)
        if m == c:  # a bucket that feeds itself goes in rounds
            at, seeded, look, m = bounds[c], bounds[c] + n_large[c], 1, c + 1
            while at < (upto := int(free[c])):
                up.push(*up.fed(slots[at:upto])[1:])
                at = upto
            up.push(*up.fed(slots[seeded : bounds[m]])[1:])
        c = m


def downwards(down: Buckets, n_large: list[int], k: int) -> None:
    """Fills in the smaller types, from the last bucket to the first."""
    bounds, slots, free = down.bounds, down.slots, down.free
    c, look = k, 1
    while c > 0:
        m = c
        if k > SMALL_ALPHABET:
            end = max(0, c - look)
            hit, found, chars = down.fed(slots[bounds[end] : bounds[c]][::-1])
            inside = chars[chars >= end]
            m = int(inside.max()) + 1 if len(inside) else end
            if m == end:
                down.push(found, chars)
            elif m < c:
                n = hit.searchsorted(bounds[c] - bounds[m])
                down.push(found[:n], chars[:n])
            look = 2 * (c - m)
        if m == c:
            at, look, m = bounds[c], 1, c - 1
            while at > (low := int(free[m]) + 1):
                down.push(*down.fed(slots[low:at][::-1])[1:])
                at = low
            down.push(*down.fed(slots[bounds[m] : bounds[m] + n_large[m]][::-1])[1:])
        c = m


def induce(t: np.ndarray, small: np.ndarray, seeds: np.ndarray, k: int) -> np.ndarray:
    """All suffixes from leftmost-smaller ones in order: larger types left to right, smaller types right to left."""
    large = ~small
    n_large, n_small = np.bincount(t[large], minlength=k), np.bincount(t[small], minlength=k)
    seeds = seeds[t[seeds].argsort(kind="stable")]
    n_seeds = np.bincount(t[seeds], minlength=k)
    first = np.concatenate([[0], np.cumsum(n_large + n_seeds)])
    up = Buckets(t, large, first, first[:-1].copy(), 1)
    up.slots[spread(n_seeds, first[:-1] + n_large)] = seeds
    upwards(up, n_large.tolist(), k)
    second = np.concatenate([[0], np.cumsum(n_large + n_small)])
    down = Buckets(t, small, second, second[1:] - 1, -1)
    down.slots[spread(n_large, second[:-1])] = up.slots[spread(n_large, first[:-1])]
    down.push(np.array([len(t) - 1]), t[-1:])
    downwards(down, n_large.tolist(), k)
    return down.slots


def symbols(t: np.ndarray, k: int) -> np.ndarray:
    return t.astype(np.uint16 if k <= 1 << 16 else np.int32)


def ordered(t: np.ndarray, k: int, depth: int) -> np.ndarray:
    """Suffixes of t, whose last symbol 0 occurs once, in order of their first `depth` symbols at least.

    Leftmost-smaller substrings are sorted by an induction and named by their rank. Where names
    repeat, the string of names goes through the same procedure, and its suffixes' order gives the
    second induction its seeds. A name that occurs once is in place already and decides every
    comparison that comes to it; it goes along only behind a name that repeats. A name stands for
    two symbols at least, so the recursion ends.
    """
    n = len(t)
    rises = np.append(t[1:] > t[:-1], True)
    steady = np.append(t[1:] == t[:-1], False)
    following = np.where(steady, n - 1, np.arange(n, dtype=np.int32))
    small = rises[np.minimum.accumulate(following[::-1])[::-1]]
    seeds = np.flatnonzero(small[1:] & ~small[:-1]) + 1
    if len(seeds) > 1:
        order = induce(t, small, seeds, k)
        place = np.full(n, -1, np.int32)
        place[seeds] = np.arange(len(seeds))
        ends = np.append(seeds[1:], n - 1) + 1
        hashes, size = span_hashes(t, seeds, ends), ends - seeds
        at = place[order]
        at = at[at >= 0]
        new = np.ones(len(at), bool)
        new[1:] = (hashes[at[1:]] != hashes[at[:-1]]) | (size[at[1:]] != size[at[:-1]])
        if depth > 1 and not new.all():
            names = np.empty(len(at), np.int64)
            names[at] = np.cumsum(new) - 1
            tied = np.bincount(names)[names] > 1
            going = tied.copy()
            going[1:] |= tied[:-1]
            going[-1] = True
            went = np.flatnonzero(going)
            held = np.zeros(int(names[at[-1]]) + 1, np.int64)
            held[names[went]] = 1
            shorter = (np.cumsum(held) - 1)[names[went]]
            kinds = int(held.sum())
            found = went[ordered(symbols(shorter, kinds), kinds, -(-depth // 2) + 1)]
            at[tied[at]] = found[tied[found]]
        seeds = seeds[at]
    return induce(t, small, seeds, k)


def suffix_array(text: np.ndarray, depth: int) -> np.ndarray:
    """Suffix positions of text (symbols above 0) in order of their first `depth` symbols at least."""
    k = int(text.max(initial=0)) + 1
    return ordered(symbols(np.append(text, 0), k), k, depth)[1:].astype(np.int64)


def common_prefixes(text: np.ndarray, order: np.ndarray, depth: int) -> np.ndarray:
    """For each suffix in order, what it shares with the one before it, at most depth; text is long enough at all of them."""
    out = np.zeros(len(order), np.int64)
    live = np.arange(1, len(order))
    for k in range(depth):
        live = live[text[order[live] + k] == text[order[live - 1] + k]]
        if not len(live):
            break
        out[live] = k + 1
    return out


def permuted(order: np.ndarray, prefixes: np.ndarray, n: int) -> np.ndarray:
    """The same numbers by text position."""
    out = np.zeros(n, np.int64)
    out[order] = prefixes
    return out
