"""Byte-level BPE as a streaming transducer, and its incremental decoder.

Text enters in pieces and tokens leave as soon as no later input can change them.

* Pre-tokens: the splitting pattern is a finite automaton over character classes, so a
  boundary is known once one more character has been seen (white space: once the run ends).
  Boundaries of a whole piece are found with array operations.
* Inside a pre-token the merge list decides. Its sufficient lookahead is computed when the
  vocabulary is loaded (`lookahead`): tokens end at most that many bytes apart, so every
  encoding of a longer input passes through one of the last `lookahead` byte positions. A
  boundary that the best encodings ending at all those positions share is final, and what
  stands before it is emitted (`Transducer`). Long pre-tokens go that way; short ones of a
  piece are merged together, round by round, as arrays.
* Words repeat, so their ids are kept in a hash table of bounded size, emptied when full.

Memory depends on the piece length, the table and the longest undecided stretch, not on the
length of the text.
"""

from __future__ import annotations

import codecs
import json
from collections.abc import Callable, Iterator

import numpy as np
import regex

from .common import span_hashes

SPECIAL = "<|endoftext|>"
OTHER, LETTER, NUMBER, SPACE = 0, 1, 2, 3
PIECE = 1 << 19
PAIR_BITS = 18


def byte_alphabet() -> list[str]:
    """The printable stand-in of every byte in vocabulary files of this kind."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    out, spare = [""] * 256, 256
    for b in range(256):
        if b in plain:
            out[b] = chr(b)
        else:
            out[b] = chr(spare)
            spare += 1
    return out


_CLASSES: list[np.ndarray] = []


def classes() -> np.ndarray:
    """The class of every code point for the splitting pattern."""
    if not _CLASSES:
        table = np.zeros(0x110000, np.uint8)
        every = "".join(map(chr, range(0xD800))) + "".join(map(chr, range(0xE000, 0x110000)))
        for kind, pattern in ((LETTER, r"\p{L}+"), (NUMBER, r"\p{N}+"), (SPACE, r"\s+")):
            for m in regex.finditer(pattern, every):
                for a, b in ((m.start(), min(m.end(), 0xD800)), (max(m.start(), 0xD800) + 0x800, m.end() + 0x800)):
                    if a < b:
                        table[a:b] = kind
        _CLASSES.append(table)
    return _CLASSES[0]


def pretoken_starts(codes: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Where pre-tokens start in joined texts; bounds: where each non-empty text starts."""
    n = len(codes)
    kind = classes()[codes]
    first = np.zeros(n + 1, bool)
    first[bounds] = True
    first[n] = True
    start = np.empty(n, bool)
    start[0] = True
    np.not_equal(kind[1:], kind[:-1], out=start[1:])
    start |= first[:n]
    # The last character of a run of white space stands before a word of the same text: it is
    # a pre-token of its own, and a plain blank joins the word.
    blank = kind == SPACE
    last = np.flatnonzero(blank[:-1] & ~blank[1:] & ~first[1:n]) if n > 1 else np.empty(0, np.int64)
    start[last] = True
    joined = last[codes[last] == 32] + 1
    start[joined] = False
    # Contractions: an apostrophe that starts a pre-token and is followed by one of the endings.
    quote = np.flatnonzero((codes == 39) & start)
    for q in quote.tolist():
        e = q + 1
        if e >= n or first[e] or kind[e] != LETTER:
            continue
        two = "".join(map(chr, codes[e : e + 2].tolist())) if e + 1 < n and not first[e + 1] else ""
        size = 1 if chr(codes[e]) in "stmd" else 2 if two in ("re", "ve", "ll") else 0
        if size:
            start[e] = False
            if e + size < n:
                start[e + size] = True
    return np.flatnonzero(start)


class WordTable:
    """An open-addressing hash table from 64-bit word hashes to runs of ids, of bounded size."""

    def __init__(self, bits: int = 21, most_ids: int = 1 << 22) -> None:
        self.bits, self.most_ids = bits, most_ids
        self.clear()

    def clear(self) -> None:
        size = 1 << self.bits
        self.keys, self.at, self.length = np.zeros(size, np.uint64), np.zeros(size, np.int32), np.zeros(size, np.int32)
        self.ids, self.used, self.count = np.empty(1 << 16, np.uint16), 0, 0

    def find(self, keys: np.ndarray) -> np.ndarray:
        """The slot of each key, -1 where it is absent. No key is 0."""
        mask = np.int64((1 << self.bits) - 1)
        slot = (keys >> np.uint64(64 - self.bits)).astype(np.int64)
        out, todo = np.full(len(keys), -1, np.int64), None
        while True:
            got = self.keys[slot]
            want = keys if todo is None else keys[todo]
            hit, gone = got == want, got == 0
            if todo is None:
                out[hit] = slot[hit]
                todo = np.flatnonzero(~hit & ~gone)
                slot = (slot[todo] + 1) & mask
            else:
                out[todo[hit]] = slot[hit]
                keep = ~hit & ~gone
                slot, todo = (slot[keep] + 1) & mask, todo[keep]
            if not len(todo):
                return out

    def add(self, keys: np.ndarray, ids: np.ndarray, lengths: np.ndarray) -> None:
        """Add distinct absent keys; ids: their runs, one after another."""
        if self.count + len(keys) > 1 << (self.bits - 1) or self.used + len(ids) > self.most_ids:
            self.clear()
        if self.used + len(ids) > len(self.ids):
            self.ids = np.concatenate([self.ids[: self.used], np.empty(max(len(ids), len(self.ids)), np.uint16)])
        self.ids[self.used : self.used + len(ids)] = ids
        offsets = self.used + np.cumsum(lengths) - lengths
        self.used, self.count = self.used + len(ids), self.count + len(keys)
        if len(keys) > 1 << (self.bits - 1):
            self.bits = int(len(keys)).bit_length() + 1
            used, held = self.used, self.ids
            self.keys, self.at, self.length = (np.zeros(1 << self.bits, t) for t in (np.uint64, np.int32, np.int32))
            self.used, self.ids = used, held
        mask = np.int64((1 << self.bits) - 1)
        slot, left = (keys >> np.uint64(64 - self.bits)).astype(np.int64), np.arange(len(keys))
        while len(left):
            free = self.keys[slot] == 0
            _, winner = np.unique(np.where(free, slot, -1 - np.arange(len(slot))), return_index=True)
            winner = winner[free[winner]]
            self.keys[slot[winner]] = keys[left[winner]]
            self.at[slot[winner]] = offsets[left[winner]]
            self.length[slot[winner]] = lengths[left[winner]]
            keep = np.ones(len(left), bool)
            keep[winner] = False
            slot, left = (slot[keep] + 1) & mask, left[keep]


def gather_runs(values: np.ndarray, at: np.ndarray, length: np.ndarray) -> np.ndarray:
    """values[at[i]:at[i]+length[i]] for every i, one after another."""
    total = np.cumsum(length)
    if not len(total) or not total[-1]:
        return values[:0]
    return values[np.arange(total[-1]) + np.repeat(at - (total - length), length)]


class Vocabulary:
    """The tokens and merges of a byte-level BPE file."""

    def __init__(self, path: str) -> None:
        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        back = {c: b for b, c in enumerate(byte_alphabet())}
        self.vocab = {bytes(map(back.__getitem__, t)): i for t, i in model["vocab"].items()}
        self.size = max(self.vocab.values()) + 2
        self.bytes_of: list[bytes] = [b""] * self.size
        for t, i in self.vocab.items():
            self.bytes_of[i] = t
        self.bytes_of[self.size - 1] = SPECIAL.encode()
        self.byte_ids = np.array([self.vocab[bytes([b])] for b in range(256)], np.int64)
        pairs = [m if isinstance(m, list) else m.split(" ") for m in model["merges"]]
        left, right = ([self.vocab[bytes(map(back.__getitem__, p[k]))] for p in pairs] for k in (0, 1))
        made = [self.vocab[self.bytes_of[a] + self.bytes_of[b]] for a, b in zip(left, right, strict=True)]
        self.slots, self.slot_rank, self.slot_made = (np.full(1 << PAIR_BITS, -1, np.int64) for _ in range(3))
        for r, (a, b, c) in enumerate(zip(left, right, made, strict=True)):
            key = a << 16 | b
            slot = (key * 0x9E3779B97F4A7C15 & (1 << 64) - 1) >> 64 - PAIR_BITS
            while self.slots[slot] >= 0:
                slot = (slot + 1) & (1 << PAIR_BITS) - 1
            self.slots[slot], self.slot_rank[slot], self.slot_made[slot] = key, r, c
        self.by_pair = {(a, b): (r, c) for r, (a, b, c) in enumerate(zip(left, right, made, strict=True))}
        #: No merge makes a token of more bytes than this.
        self.lookahead = max(len(self.bytes_of[c]) for c in made)
        self.blob = np.frombuffer(b"".join(self.bytes_of), np.uint8)
        self.blob_length = np.array([len(t) for t in self.bytes_of], np.int64)
        self.blob_at = np.cumsum(self.blob_length) - self.blob_length

    def ranks(self, symbol: np.ndarray, owner: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rank and result of the merge of each symbol at `at` with the next one of its word."""
        rank, made = np.full(len(at), 1 << 30, np.int64), np.zeros(len(at), np.int64)
        inside = np.flatnonzero(at + 1 < len(symbol))
        inside = inside[owner[at[inside]] == owner[at[inside] + 1]]
        keys = symbol[at[inside]] << 16 | symbol[at[inside] + 1]
        slot = (keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - PAIR_BITS)).astype(np.int64)
        left = np.arange(len(keys))
        while len(left):
            got = self.slots[slot]
            hit = got == keys[left]
            rank[inside[left[hit]]], made[inside[left[hit]]] = self.slot_rank[slot[hit]], self.slot_made[slot[hit]]
            more = ~hit & (got >= 0)
            slot, left = (slot[more] + 1) & ((1 << PAIR_BITS) - 1), left[more]
        return rank, made

    def merge(self, data: bytes) -> list[int]:
        """Plain merging of a short string, lowest rank first."""
        ids = self.byte_ids[np.frombuffer(data, np.uint8)].tolist()
        while len(ids) > 1:
            best = min(((self.by_pair.get(p, (1 << 30, 0)), p) for p in zip(ids, ids[1:], strict=False)), key=lambda x: x[0])
            if best[0][0] == 1 << 30:
                break
            out, k = [], 0
            while k < len(ids):
                if k + 1 < len(ids) and (ids[k], ids[k + 1]) == best[1]:
                    out.append(best[0][1])
                    k += 2
                else:
                    out.append(ids[k])
                    k += 1
            ids = out
        return ids

    def merge_many(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all words, one after another, and how many each word has."""
        lengths = np.array([len(w) for w in words], np.int64)
        symbol = self.byte_ids[np.frombuffer(b"".join(words), np.uint8)]
        owner = np.repeat(np.arange(len(words)), lengths)
        done: list[tuple[np.ndarray, np.ndarray]] = []
        none = np.int64(1 << 30)
        rank, made = self.ranks(symbol, owner, np.arange(len(symbol)))
        while len(symbol):
            begins = np.flatnonzero(np.concatenate([[True], owner[1:] != owner[:-1]]))
            least = np.minimum.reduceat(rank, begins)
            counts = np.diff(np.append(begins, len(symbol)))
            keep = np.repeat(least < none, counts)
            done.append((owner[~keep], symbol[~keep]))
            hit = np.flatnonzero((rank == np.repeat(least, counts)) & keep)
            if len(hit):  # of overlapping pairs (a run of one symbol) every other one counts, from the left
                fresh = np.concatenate([[True], hit[1:] != hit[:-1] + 1])
                begin = np.flatnonzero(fresh)
                place = np.arange(len(hit)) - np.repeat(begin, np.diff(np.append(begin, len(hit))))
                hit = hit[place % 2 == 0]
                symbol[hit] = made[hit]
                keep[hit + 1] = False
            moved = np.cumsum(keep) - 1
            symbol, owner, rank, made = symbol[keep], owner[keep], rank[keep], made[keep]
            changed = np.zeros(len(symbol) + 1, bool)
            changed[moved[hit]] = True
            changed[moved[hit] - 1] = True
            new = np.flatnonzero(changed[:-1])
            rank[new], made[new] = self.ranks(symbol, owner, new)
        owners, symbols = (np.concatenate([d[k] for d in done]) if done else np.empty(0, np.int64) for k in (0, 1))
        order = np.argsort(owners, kind="stable")
        return symbols[order], np.bincount(owners, minlength=len(words))


class Transducer:
    """Ids of one long pre-token, fed byte by byte and emitted once they are final.

    For every prefix there is one token that ends its encoding: the one that stays apart from
    the token before it when the two are merged together. last[i] is that token's length at
    byte i of the buffer. Encodings of longer inputs pass through one of the last `lookahead`
    positions; a boundary through which the chains of all of them run is final.
    """

    def __init__(self, vocabulary: Vocabulary, cache: dict | None = None) -> None:
        self.v, self.cache = vocabulary, {} if cache is None else cache
        self.buffer, self.last, self.token = b"", [0], [-1]

    def apart(self, a: int, b: int) -> bool:
        got = self.cache.get((a, b))
        if got is None:
            if len(self.cache) > 200_000:
                self.cache.clear()
            got = self.cache[a, b] = self.v.merge(self.v.bytes_of[a] + self.v.bytes_of[b]) == [a, b]
        return got

    def feed(self, data: bytes) -> list[int]:
        out: list[int] = []
        for b in data:
            self.buffer += bytes([b])
            i = len(self.buffer)
            for size in range(min(self.v.lookahead, i), 0, -1):
                t = self.v.vocab.get(self.buffer[i - size :])
                if t is not None and self.v.merge(self.v.bytes_of[t]) == [t] and (i == size and self.token[0] < 0 or self.apart(self.token[i - size], t)):
                    self.last.append(size)
                    self.token.append(t)
                    break
            if i >= 4 * self.v.lookahead:
                out += self.emit()
        return out

    def chain(self, i: int) -> list[int]:
        at = []
        while i > 0:
            at.append(i)
            i -= self.last[i]
        return at[::-1]

    def emit(self) -> list[int]:
        n = len(self.buffer)
        common = set(self.chain(n))
        for i in range(n - self.v.lookahead + 1, n):
            common &= set(self.chain(i))
        if not common:
            return []
        cut = max(common)
        out = [self.token[i] for i in self.chain(cut)]
        self.buffer, self.last, self.token = self.buffer[cut:], [0, *self.last[cut + 1 :]], [self.token[cut], *self.token[cut + 1 :]]
        return out

    def finish(self) -> list[int]:
        return [self.token[i] for i in self.chain(len(self.buffer))]


class Encoder:
    """Encodes many texts; words: how ids of unseen words are made (default: the merge list)."""

    LONG = 512

    def __init__(self, vocabulary: Vocabulary, words: Callable[[list[str]], tuple[np.ndarray, np.ndarray]] | None = None) -> None:
        self.v, self.table, self.cache = vocabulary, WordTable(), {}
        self.words = words or self.merged

    def merged(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        raw = [w.encode("utf-8", "surrogatepass") for w in words]
        long = {k: w for k, w in enumerate(raw) if len(w) > self.LONG}
        ids, lengths = self.v.merge_many([b"" if k in long else w for k, w in enumerate(raw)])
        if not long:
            return ids, lengths
        ends = np.cumsum(lengths)
        parts = []
        for k in range(len(raw)):
            if k in long:
                machine = Transducer(self.v, self.cache)
                got = machine.feed(long[k])
                parts.append(np.array(got + machine.finish(), np.int64))
                lengths[k] = len(parts[-1])
            else:
                parts.append(ids[ends[k] - lengths[k] : ends[k]])
        return np.concatenate(parts), lengths

    def piece(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of short texts without special tokens, one after another, and each text's count."""
        joined = "".join(texts)
        size = np.array([len(t) for t in texts], np.int64)
        if not joined:
            return np.empty(0, np.uint16), np.zeros(len(texts), np.int64)
        codes = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
        ends = np.cumsum(size)
        starts = pretoken_starts(codes, (ends - size)[size > 0])
        stops = np.append(starts[1:], len(codes))
        keys = span_hashes(codes, starts, stops)
        keys[keys == 0] = 1
        slot = self.table.find(keys)
        miss = np.flatnonzero(slot < 0)
        if len(miss):
            fresh, first = np.unique(keys[miss], return_index=True)
            at = miss[first]
            ids, lengths = self.words([joined[a:b] for a, b in zip(starts[at].tolist(), stops[at].tolist(), strict=True)])
            before = self.table.count
            self.table.add(fresh, ids, lengths)
            if self.table.count < before + len(fresh):  # emptied: what was known is unknown again
                slot = self.table.find(keys)
                gone = np.flatnonzero(slot < 0)
                if len(gone):
                    more, first = np.unique(keys[gone], return_index=True)
                    at = gone[first]
                    ids, lengths = self.words([joined[a:b] for a, b in zip(starts[at].tolist(), stops[at].tolist(), strict=True)])
                    self.table.most_ids = max(self.table.most_ids, 2 * (self.table.used + len(ids)))
                    self.table.bits = max(self.table.bits, int(self.table.count + len(more)).bit_length() + 1)
                    if len(self.table.keys) != 1 << self.table.bits:
                        self.table.clear()
                        every, first = np.unique(keys, return_index=True)
                        ids, lengths = self.words([joined[a:b] for a, b in zip(starts[first].tolist(), stops[first].tolist(), strict=True)])
                        more = every
                    self.table.add(more, ids, lengths)
                slot = self.table.find(keys)
            else:
                slot[miss] = self.table.find(keys[miss])
        length = self.table.length[slot]
        total = np.concatenate([[0], np.cumsum(length, dtype=np.int64)])
        return gather_runs(self.table.ids, self.table.at[slot].astype(np.int64), length.astype(np.int64)), total[np.searchsorted(starts, ends)] - total[np.searchsorted(starts, ends - size)]

    def pieces(self, text: str) -> Iterator[str]:
        """A long text cut at places where a pre-token surely ends: before a blank between two words."""
        at = 0
        while len(text) - at > PIECE:
            cut = at + PIECE
            found = CUT.search(text, cut)
            if not found:
                break
            yield text[at : found.start() + 1]
            at = found.start() + 1
        yield text[at:]

    def encode(self, texts: list[str]) -> Iterator[np.ndarray]:
        """The ids of each text, in order."""
        held: list[str] = []
        size = 0
        for text in texts:
            if len(text) <= PIECE and SPECIAL not in text:
                held.append(text)
                size += len(text)
                if size > PIECE:
                    yield from self.flush(held)
                    held, size = [], 0
                continue
            yield from self.flush(held)
            held, size = [], 0
            out = []
            for k, part in enumerate(text.split(SPECIAL)):
                if k:
                    out.append(np.array([self.v.size - 1], np.uint16))
                out += [self.piece([p])[0] for p in self.pieces(part)]
            yield np.concatenate(out)
        yield from self.flush(held)

    def flush(self, texts: list[str]) -> Iterator[np.ndarray]:
        if texts:
            ids, counts = self.piece(texts)
            yield from np.split(ids, np.cumsum(counts)[:-1])


CUT = regex.compile(r"\p{L}(?= \p{L})")


class Decoder:
    """Bytes of ids to text, piece by piece; an unfinished character waits for its next bytes."""

    def __init__(self, vocabulary: Vocabulary) -> None:
        self.v = vocabulary
        self.machine = codecs.getincrementaldecoder("utf-8")("replace")

    def feed(self, ids: np.ndarray) -> str:
        ids = ids.astype(np.int64)
        data = gather_runs(self.v.blob, self.v.blob_at[ids], self.v.blob_length[ids]).tobytes()
        return self.machine.decode(data)

    def finish(self) -> str:
        return self.machine.decode(b"", final=True)
