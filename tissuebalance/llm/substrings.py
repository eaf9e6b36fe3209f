"""Repeated byte strings across documents, through suffix arrays of shards.

A byte goes if a string of `length` bytes that covers it also starts in a document with a
smaller id. Windows of that length are told apart by their smallest k-byte piece (by hash, the
leftmost of equals): equal windows have equal pieces. Runs of windows with one such piece are
what travels:

1. Groups of neighbouring ids list the hashes of their pieces, each once.
2. Hashes listed by two groups, or by two documents of one group, are sent back to the groups.
3. Groups send the runs of those pieces to the hash's shard, where each distinct text of a run
   goes once per group, with its smallest id; for larger ids in the group nothing is left to ask.
4. A shard joins its distinct texts, builds their suffix array, and finds for each window the
   smallest id among the suffixes that share its first `length` bytes with it.
5. Groups cut what was found out of their documents.

A group's size in bytes is bounded: the larger long documents are, the fewer ids share their groups. A piece
that very many groups list is heavy. Its runs are cut in two where the piece stands in the first
or second half of a window, and go to shards by the bytes that all windows of such a half share
beside the piece; equal runs of one shard are first reduced over parts of the groups. So neither
a phrase that stands in many contexts nor a passage that all documents hold fills one task.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Workspace, batch, mix64, span_hashes, tasks_for
from .suffixes import common_prefixes, permuted, spread, suffix_array

LENGTH, PIECE = 50, 16
SHARD_BYTES, CHUNK = 4 << 20, 1 << 18
#: Bytes of a usual group: about a thousandth of all within these bounds (powers of two); and of any with several documents.
GROUP_BITS, GROUP_MOST, TASK_BYTES = (21, 25), 64 << 20, 16 << 20
#: Groups that make a piece heavy, and parts over which its equal runs are reduced.
HEAVY, PARTS = 4096, 64
#: Bounds of how far before their piece windows of one part begin: those of halves, and of what the suffix array gets.
HALVES, NARROW = (0, 18, 35), (0, 6, 12, 18, 24, 30, 35)
#: What is listed of a hash beside its shard.
LOW_BITS = np.uint64(39)
LOW = (np.uint64(1) << LOW_BITS) - np.uint64(1)
LAST = (1 << 63) - 1


def runs(raw: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of joined texts: text, first byte, end, piece position and hash of each run of windows with one smallest piece."""
    return runs_of(np.frombuffer(b"".join(raw), np.uint8), np.array([len(r) for r in raw], np.int64))


def runs_of(b: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    ends = np.cumsum(size)
    none = tuple(np.empty(0, np.int64) for _ in range(4))
    if len(b) < LENGTH:
        return *none, np.empty(0, np.uint64)
    h, width, base = b.astype(np.uint64) + np.uint64(1), 1, np.uint64(0x9E3779B97F4A7C15)
    with np.errstate(over="ignore"):
        while width < PIECE:  # PIECE is a power of two
            h = h[:-width] * base + h[width:]
            base, width = base * base, 2 * width
        h = mix64(h) >> np.uint64(1)
    # Hash and position in one number: the least of a window is its smallest piece, leftmost of equals.
    bits = np.uint64(36)  # the same for all pieces, so that ties of the rest fall alike everywhere
    low, have, want = (h >> bits << bits) | np.arange(len(h), dtype=np.uint64), 1, LENGTH - PIECE + 1
    while have < want:
        step = min(have, want - have)
        low = np.minimum(low[: len(low) - step], low[step:])
        have += step
    at = (low & ((np.uint64(1) << bits) - np.uint64(1))).astype(np.int64)
    text = np.repeat(np.arange(len(size)), size)[: len(at)]
    ok = np.arange(len(at)) + LENGTH <= ends[text]
    change = np.ones(len(at), bool)
    change[1:] = (at[1:] != at[:-1]) | ~ok[:-1] | (text[1:] != text[:-1])
    first = np.flatnonzero(change & ok)
    stop = np.ones(len(at), bool)
    stop[:-1] = change[1:] | ~ok[1:]
    last = np.flatnonzero(stop & ok)
    return text[first], first, last + LENGTH, at[first], h[at[first]]


def pack(a: np.ndarray, kind: str) -> bytes:
    return a.astype(kind).tobytes()


def five(values: np.ndarray) -> np.ndarray:
    """Numbers below 2**40 as rows of five bytes."""
    return np.ascontiguousarray(values.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :5])


def unfive(column: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """All numbers of such a column, and how many each row has."""
    counts = np.array([len(x.as_py()) // 5 for x in column], np.int64)
    out = np.zeros((counts.sum(), 8), np.uint8)
    if len(out):
        out[:, :5] = np.frombuffer(b"".join(x.as_py() for x in column), np.uint8).reshape(-1, 5)
    return out.view("<u8").ravel(), counts


def shard_of(h: np.ndarray, shards: int) -> np.ndarray:
    return (mix64(h) % np.uint64(shards)).astype(np.int64)


def sorted_rows(table: pa.Table) -> tuple[np.ndarray, list[bytes], np.ndarray]:
    """Ids, texts and original places of a group's rows, in an order that does not depend on how they came."""
    ids = table.column("doc").to_numpy()
    raw = [x.as_py() for x in table.column("raw")]
    order = sorted(range(len(raw)), key=lambda k: (ids[k], raw[k]))
    return ids[order], [raw[k] for k in order], np.array(order, np.int64)


def parts(raw: list[bytes]) -> Iterator[tuple[int, int]]:
    start, size = 0, 0
    for k, r in enumerate(raw):
        if size and size + len(r) > CHUNK:
            yield start, k
            start, size = k, 0
        size += len(r)
    if start < len(raw):
        yield start, len(raw)


def listed(it: Iterator[pa.RecordBatch], shards: int) -> Iterator[pa.RecordBatch]:
    """Low bits of the pieces' hashes by shard and group; the lowest bit says that two documents have it."""
    schema = pa.schema([("shard", pa.int64()), ("group", pa.int64()), ("hashes", pa.binary())])
    for got in it:
        group, ids, every = got.column("group").to_numpy(), got.column("doc").to_numpy(), got.column("raw").to_pylist()
        for g in np.unique(group):
            own = np.flatnonzero(group == g)
            raw, own_ids = [every[k] for k in own], ids[own]
            found: list[np.ndarray] = []
            docs: list[np.ndarray] = []
            for a, b in parts(raw):
                text, _, _, _, h = runs(raw[a:b])
                found.append(h)
                docs.append(own_ids[a:b][text])
            h, d = np.concatenate(found), np.concatenate(docs)
            if not len(h):
                continue
            order = np.argsort(h)
            h, d = h[order], d[order]
            begin = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1]]))
            several = np.minimum.reduceat(d, begin) != np.maximum.reduceat(d, begin)
            value = (h[begin] & LOW) << np.uint64(1) | several.astype(np.uint64)
            shard = shard_of(h[begin], shards)
            order = np.argsort(shard, kind="stable")
            value, shard = value[order], shard[order]
            cuts = np.flatnonzero(np.diff(shard)) + 1
            blobs = [x.tobytes() for x in np.split(five(value), cuts)]
            yield batch(schema, shard[np.append(0, cuts)], np.full(len(blobs), g), blobs)


HOT = "group bigint, shard bigint, hashes binary"
HOT_ARROW = pa.schema([("group", pa.int64()), ("shard", pa.int64()), ("hashes", pa.binary())])


def shared(table: pa.Table, heavy: int) -> pa.Table:
    """Of one shard: for each group the hashes that more than one document has; the lowest bit says that `heavy` groups have it."""
    values, counts = unfive(table.column("hashes"))
    owner = np.repeat(table.column("group").to_numpy(), counts)
    h, flag = values >> np.uint64(1), (values & np.uint64(1)).astype(bool)
    order = np.argsort(h, kind="stable")
    h, flag, owner = h[order], flag[order], owner[order]
    begin = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1]]))
    count = np.diff(np.append(begin, len(h)))
    hot = (count > 1) | np.logical_or.reduceat(flag, begin)
    keep = np.repeat(hot, count)
    h, owner = (h << np.uint64(1) | np.repeat(count >= heavy, count).astype(np.uint64))[keep], owner[keep]
    order = np.argsort(owner, kind="stable")
    h, owner = h[order], owner[order]
    cuts = np.flatnonzero(np.diff(owner)) + 1
    blobs = [x.tobytes() for x in np.split(five(h), cuts)] if len(h) else []
    groups = owner[np.append(0, cuts)] if len(h) else np.empty(0, np.int64)
    shard = np.full(len(blobs), table.column("shard")[0].as_py())
    return pa.table([pa.array(groups), pa.array(shard, pa.int64()), pa.array(blobs, pa.binary())], schema=HOT_ARROW)


#: shard -1: bytes to cut from rows of the group; else runs to be judged in that shard, those of part >= 0 after a reduction.
RUNS = "shard bigint, part int, group bigint, row binary, start binary, size binary, doc binary, text binary"
RUNS_ARROW = pa.schema([("shard", pa.int64()), ("part", pa.int32()), ("group", pa.int64()), *((n, pa.binary()) for n in ("row", "start", "size", "doc", "text"))])
CUTS = "group bigint, row binary, start binary, size binary"
CUTS_ARROW = pa.schema([("group", pa.int64()), *((n, pa.binary()) for n in ("row", "start", "size"))])
#: A run has LENGTH - PIECE + 1 windows at most, so its size fits a byte.
ROW, START, SIZE, DOC = "<i4", "<u4", "<u1", "<i8"


def numbers(table: pa.Table, name: str, kind: str) -> np.ndarray:
    return np.concatenate([np.frombuffer(x.as_buffer(), kind) for x in table.column(name)]).astype(np.int64)


def gather(b: np.ndarray, start: np.ndarray, size: np.ndarray) -> bytes:
    return b[spread(size, start)].tobytes() if len(size) else b""


def gathered(texts: list[tuple[np.ndarray, np.ndarray]], chunk: np.ndarray, first: np.ndarray, size: np.ndarray, upto: np.ndarray) -> np.ndarray:
    """The bytes of all runs, each from its chunk, in their order. Chunks are gone through once, however many shards there are."""
    out = np.empty(upto[-1], np.uint8)
    for p, (b, _) in enumerate(texts):
        own = np.flatnonzero(chunk == p)
        if len(own):
            out[spread(size[own], upto[own])] = b[spread(size[own], first[own])]
    return out


def bands(b: np.ndarray, first: np.ndarray, end: np.ndarray, at: np.ndarray, edges: tuple[int, ...]) -> tuple[np.ndarray, ...]:
    """Runs cut by how far before the piece, from one edge to the next, their windows begin: which run, first byte,
    end, and a hash of the bytes that all windows of such a part share. Equal windows are in parts of one hash."""
    which = np.arange(len(first))
    out = []
    for side, (near, far) in enumerate(zip(edges, edges[1:], strict=False)):
        lo, hi = np.maximum(first, at - far + 1), np.minimum(end, at - near + LENGTH)
        has = lo + LENGTH <= hi
        key = mix64(span_hashes(b, (at - near)[has], (at - far + 1 + LENGTH)[has]) + np.uint64(side))
        out.append((which[has], lo[has], hi[has], key))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def equal_runs(key: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """An order by key and document, where runs of one text begin in it, and the smallest document of each run's text."""
    order = np.lexsort((doc, key))
    begin = np.flatnonzero(np.concatenate([[True], key[order][1:] != key[order][:-1]]))
    least = np.empty(len(key), np.int64)
    least[order] = np.repeat(doc[order[begin]], np.diff(np.append(begin, len(key))))
    return order, begin, least


def sent(docs: pa.Table, hot: pa.Table, shards: int, n_parts: int) -> pa.Table:
    """The runs of one group that may repeat, to the shards of their pieces."""
    out: list[tuple] = []
    if docs.num_rows and hot.num_rows:
        group = docs.column("group")[0].as_py()
        ids, raw, _ = sorted_rows(docs)
        values, counts = unfive(hot.column("hashes"))
        known = np.repeat(hot.column("shard").to_numpy().astype(np.uint64), counts) << LOW_BITS | values >> np.uint64(1)
        order = np.argsort(known)
        known, is_heavy = known[order], (values[order] & np.uint64(1)).astype(bool)
        row, start, size, key, piece, heavy, texts = [], [], [], [], [], [], []
        for a, b in parts(raw):
            text, first, end, at, h = runs(raw[a:b])
            want = shard_of(h, shards).astype(np.uint64) << LOW_BITS | h & LOW
            place = np.searchsorted(known, want)
            place[place == len(known)] = 0
            keep = np.flatnonzero(known[place] == want)
            text, first, end, at, h, own_heavy = text[keep], first[keep], end[keep], at[keep], h[keep], is_heavy[place[keep]]
            joined = np.frombuffer(b"".join(raw[a:b]), np.uint8)
            if own_heavy.any():
                some, rest = np.flatnonzero(own_heavy), np.flatnonzero(~own_heavy)
                which, lo, hi, routed = bands(joined, first[some], end[some], at[some], HALVES)
                text, first, end = np.concatenate([text[rest], text[some][which]]), np.concatenate([first[rest], lo]), np.concatenate([end[rest], hi])
                h, own_heavy = np.concatenate([h[rest], routed]), np.arange(len(rest) + len(which)) >= len(rest)
            begin = np.cumsum([0, *(len(r) for r in raw[a:b])])[text]
            row.append(text + a)
            start.append(first - begin)
            size.append(end - first)
            piece.append(h)
            heavy.append(own_heavy)
            key.append(span_hashes(joined, first, end) if len(first) else np.empty(0, np.uint64))
            texts.append((joined, first))
        chunk = np.repeat(np.arange(len(row)), [len(x) for x in row])
        row, start, size, key, piece, heavy = (np.concatenate(x) for x in (row, start, size, key, piece, heavy))
        doc = ids[row] if len(row) else np.empty(0, np.int64)
        if len(row):
            later = doc > equal_runs(key, doc)[2]
            if later.any():
                out.append((-1, -1, group, pack(row[later], ROW), pack(start[later], START), pack(size[later], SIZE), b"", b""))
            ask = np.flatnonzero(~later)
            shard = shard_of(piece[ask], shards)
            order = np.lexsort((ask, heavy[ask], shard))
            ask, shard = ask[order], shard[order]
            upto = np.concatenate([[0], np.cumsum(size[ask])])
            bodies = gathered(texts, chunk[ask], np.concatenate([first for _, first in texts])[ask], size[ask], upto)
            cuts = np.concatenate([[0], np.flatnonzero(np.diff(shard) | np.diff(heavy[ask].astype(np.int8))) + 1, [len(ask)]]).tolist() if len(ask) else [0]
            part = int(mix64(np.array([group], np.int64).view(np.uint64))[0] % np.uint64(n_parts))
            columns = row[ask].astype(ROW), start[ask].astype(START), size[ask].astype(SIZE), doc[ask].astype(DOC)
            for a, b in zip(cuts, cuts[1:], strict=False):
                out.append((int(shard[a]), part if heavy[ask[a]] else -1, group, *(c[a:b].tobytes() for c in columns), bodies[upto[a] : upto[b]].tobytes()))
    return pa.table([pa.array([o[k] for o in out], f.type) for k, f in enumerate(RUNS_ARROW)], schema=RUNS_ARROW)


def opened(table: pa.Table) -> tuple[np.ndarray, ...]:
    """Group, row, start, size, document and last byte's end of each run of a shard, and all its bytes."""
    counts = [len(x.as_py()) // 4 for x in table.column("row")]
    size = numbers(table, "size", SIZE)
    b = np.frombuffer(b"".join(x.as_py() for x in table.column("text")), np.uint8)
    return np.repeat(table.column("group").to_numpy(), counts), numbers(table, "row", ROW), numbers(table, "start", START), size, numbers(table, "doc", DOC), np.cumsum(size), b


def by_group(group: np.ndarray, *columns: np.ndarray) -> Iterator[tuple[int, list[np.ndarray]]]:
    order = np.argsort(group, kind="stable")
    group, columns = group[order], tuple(c[order] for c in columns)
    cuts = np.concatenate([[0], np.flatnonzero(np.diff(group)) + 1, [len(group)]]).tolist() if len(group) else [0]
    for a, b in zip(cuts, cuts[1:], strict=False):
        yield int(group[a]), [c[a:b] for c in columns]


def reduced(table: pa.Table) -> pa.Table:
    """Of one part of a shard's heavy runs: those of each distinct text's smallest document; all others are cut."""
    group, row, start, size, doc, ends, b = opened(table)
    least = equal_runs(span_hashes(b, ends - size, ends), doc)[2]
    shard = table.column("shard")[0].as_py()
    later = doc > least
    out = [(-1, -1, g, pack(r, ROW), pack(s, START), pack(n, SIZE), b"", b"") for g, (r, s, n) in by_group(group[later], row[later], start[later], size[later])]
    first = np.flatnonzero(doc == least)
    for g, (r, s, n, d, e) in by_group(group[first], row[first], start[first], size[first], doc[first], ends[first]):
        out.append((shard, -1, g, pack(r, ROW), pack(s, START), pack(n, SIZE), pack(d, DOC), gather(b, e - n, n)))
    return pa.table([pa.array([o[k] for o in out], f.type) for k, f in enumerate(RUNS_ARROW)], schema=RUNS_ARROW)


def contested(b: np.ndarray, size: np.ndarray, doc: np.ndarray, least: np.ndarray) -> None:
    """Sets least, for each window of the texts joined in b, to the smallest doc of a text that holds the window."""
    joined = np.ones(len(b) + len(size), np.uint16)  # symbol 1 stands between texts
    at = np.cumsum(size + 1) - size - 1
    joined[spread(size, at)] = b.astype(np.uint16) + 2
    windows = size - LENGTH + 1
    place = spread(windows, at)
    number = np.full(len(joined), -1, np.int32)
    number[place] = np.arange(len(place))
    order = suffix_array(joined, LENGTH)
    order = order[number[order] >= 0]
    same = permuted(order, common_prefixes(joined, order, LENGTH), len(joined))
    fresh = np.flatnonzero(same[order] < LENGTH)
    number = number[order]
    of_window = np.repeat(doc, windows)[number]
    least[number] = np.repeat(np.minimum.reduceat(of_window, fresh), np.diff(np.append(fresh, len(order))))


def judged(table: pa.Table) -> pa.Table:
    """Of one shard: the bytes that windows repeated from smaller ids cover, by group.

    A text that is alone with its piece, or part of one with the bytes that its windows share, has
    no window in common with another text; it is as new as its smallest document. All other parts
    go through the suffix array, each distinct text of them once.
    """
    group, row, start, size, doc, ends, b = opened(table)
    order, begin, _ = equal_runs(span_hashes(b, ends - size, ends), doc)
    firsts = order[begin]  # one run of each text, with the smallest id that has it
    which = np.empty(len(row), np.int64)
    which[order] = np.repeat(np.arange(len(begin)), np.diff(np.append(begin, len(row))))
    own = size[firsts]
    held, stops = memoryview(b), ends[firsts]
    texts = np.frombuffer(b"".join([held[s:e] for s, e in zip((stops - own).tolist(), stops.tolist(), strict=True)]), np.uint8)
    windows = own - LENGTH + 1
    upto = np.cumsum(windows)
    least = np.repeat(doc[firsts], windows)
    upon = np.concatenate([[0], np.cumsum(own)])
    cuts = np.unique([0, *np.searchsorted(upon, np.arange(CHUNK, upon[-1], CHUNK)), len(own)]).tolist()
    found = [runs_of(texts[upon[a] : upon[z]], own[a:z]) for a, z in zip(cuts, cuts[1:], strict=False)]
    inside, pieces = np.concatenate([at - first for _, first, _, at, _ in found]), np.concatenate([h for *_, h in found])
    _, piece = np.unique(pieces, return_inverse=True)
    some = np.flatnonzero(np.bincount(piece)[piece] > 1)
    if len(some):
        joined, long = texts[spread(own[some], upon[some])], own[some]
        at = np.cumsum(long) - long
        half, lo, hi, key = bands(joined, at, at + long, at + inside[some], HALVES)
        _, key = np.unique(key, return_inverse=True)
        met = np.flatnonzero(np.bincount(key)[key] > 1)
        if len(met):
            band, lo, hi, key = bands(joined, lo[met], hi[met], (at + inside[some])[half[met]], NARROW)
            run = half[met][band]
            place = (upto - windows)[some][run] + lo - at[run]
            of_doc, n = doc[firsts[some]][run], hi - lo - LENGTH + 1
            order, begin, _ = equal_runs(span_hashes(joined, lo, hi), of_doc)
            ones = order[begin]  # one part of each text, with the smallest id that has it
            copies = np.diff(np.append(begin, len(order)))
            kind = np.empty(len(order), np.int64)
            kind[order] = np.repeat(np.arange(len(begin)), copies)
            of_window, base = np.repeat(of_doc[ones], n[ones]), np.cumsum(n[ones]) - n[ones]
            _, key = np.unique(key[ones], return_inverse=True)
            several = np.bincount(key)[key] > 1
            if several.any():
                own = ones[several]
                of_own = np.empty(int(n[own].sum()), np.int64)
                contested(joined[spread((hi - lo)[own], lo[own])], (hi - lo)[own], of_doc[own], of_own)
                of_window[spread(n[own], base[several])] = of_own
            told = np.flatnonzero((several | (copies > 1))[kind])
            if len(told):
                least[spread(n[told], place[told])] = of_window[spread(n[told], base[kind[told]])]
    base, out = (upto - windows)[which], []
    for a in range(0, len(row), CHUNK // 4):
        n = (size[a : a + CHUNK // 4] - LENGTH + 1)
        entry = a + np.repeat(np.arange(len(n)), n)
        step = spread(n, np.zeros(len(n), np.int64))
        hit = least[base[entry] + step] < doc[entry]
        edge = np.concatenate([[True], entry[1:] != entry[:-1]])
        begin = np.flatnonzero(hit & (edge | ~np.concatenate([[False], hit[:-1]])))
        last = np.flatnonzero(hit & np.concatenate([edge[1:] | ~hit[1:], [True]]))
        out.append((entry[begin], step[begin], step[last] - step[begin] + LENGTH))
    entry, step, long = (np.concatenate(x) for x in zip(*out, strict=True))
    found = by_group(group[entry], row[entry], start[entry] + step, long)
    rows = [(g, pack(r, ROW), pack(s, START), pack(z, SIZE)) for g, (r, s, z) in found]
    return pa.table([pa.array([r[k] for r in rows], f.type) for k, f in enumerate(CUTS_ARROW)], schema=CUTS_ARROW)


RESULT = "doc_id bigint, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string"
RESULT_ARROW = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string())])


def cut(docs: pa.Table, cuts: pa.Table) -> pa.Table:
    out: list[tuple] = []
    if docs.num_rows:
        ids, raw, order = sorted_rows(docs)
        true_ids = docs.column("doc_id").take(pa.array(order)).to_pylist()
        if cuts.num_rows:
            row, start, size = numbers(cuts, "row", ROW), numbers(cuts, "start", START), numbers(cuts, "size", SIZE)
            sort = np.argsort(row, kind="stable")
            row, start, size = row[sort], start[sort], size[sort]
        else:
            row = start = size = np.empty(0, np.int64)
        marks = np.searchsorted(row, np.arange(len(raw) + 1))
        for k, r in enumerate(raw):
            b = np.frombuffer(r, np.uint8)
            own = slice(marks[k], marks[k + 1])
            cover = np.zeros(len(b) + 1, np.int64)
            np.add.at(cover, start[own], 1)
            np.add.at(cover, start[own] + size[own], -1)
            gone = np.cumsum(cover)[:-1] > 0
            spans = int((gone & ~np.concatenate([[False], gone[:-1]])).sum()) if len(gone) else 0
            out.append((true_ids[k], len(b), int(gone.sum()), spans, hashlib.sha256(b[~gone].tobytes()).hexdigest()))
    return pa.table([pa.array([o[k] for o in out], f.type) for k, f in enumerate(RESULT_ARROW)], schema=RESULT_ARROW)


def group_of(ids, text, total: int):
    """Which group a row belongs to: neighbouring ids, the fewer the larger the document is beyond a size."""
    width = min(GROUP_BITS[1], max(GROUP_BITS[0], (total >> 10).bit_length())) - 11  # with documents of two kilobytes
    doublings = F.floor(F.log2(F.greatest(F.octet_length(text) / float(GROUP_MOST >> width), F.lit(1.0)))).cast("int")
    near = F.call_function("shiftright", F.coalesce(ids, F.xxhash64(text)), F.greatest(F.lit(width) - doublings, F.lit(0)))
    return F.xxhash64(near, doublings)


def without_repeats(docs: DataFrame, heavy: int = HEAVY, n_parts: int = PARTS) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 for every row of docs (doc_id, text).

    Null texts count as empty; a null doc_id counts as larger than all others. Rows that share a
    doc_id are judged each on its own text and do not repeat one another. Extra columns are
    ignored; an empty table gives an empty result.
    """
    spark = docs.sparkSession
    space = Workspace(spark, "substrings")
    total = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    shards, tasks = max(1, -(-total // SHARD_BYTES)), tasks_for(spark, total, TASK_BYTES)
    ids, text = F.col("doc_id").cast("bigint"), F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select(ids.alias("doc_id"), F.coalesce(ids, F.lit(LAST)).alias("doc"), group_of(ids, text, total).alias("group"), text.cast("binary").alias("raw"))

    def grouped(df: DataFrame):
        return df.repartition(tasks, "group").groupBy("group")

    def sharded(df: DataFrame, *more: str):
        return df.repartition(tasks, "shard", *more).groupBy("shard", *more)

    pieces = sharded(rows.select("doc", "group", "raw").mapInArrow(lambda it: listed(it, shards), "shard bigint, group bigint, hashes binary"))
    hot = space.write(pieces.applyInArrow(lambda t: shared(t, heavy), HOT), "shared")
    del pieces
    found = space.write(grouped(rows.select("doc", "group", "raw")).cogroup(grouped(hot)).applyInArrow(lambda a, b: sent(a, b, shards, n_parts), RUNS), "runs")
    space.drop(hot)
    asked, done = found.where("shard >= 0 and part < 0"), found.where("shard < 0")
    if not (many := found.where("part >= 0")).isEmpty():
        fewer = space.write(sharded(many, "part").applyInArrow(reduced, RUNS), "fewer")
        asked, done = asked.unionByName(fewer.where("shard >= 0")), done.unionByName(fewer.where("shard < 0"))
    cuts = space.write(sharded(asked).applyInArrow(judged, CUTS).unionByName(done.select("group", "row", "start", "size")), "cuts")
    space.drop(found)
    return grouped(rows).cogroup(grouped(cuts)).applyInArrow(cut, RESULT)
