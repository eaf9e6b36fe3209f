"""Word shingles of texts as 64-bit hashes, computed on whole arrays."""

from __future__ import annotations

import numpy as np

from .common import mix64, span_hashes

_LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
_BLANK = np.zeros(256, bool)
_BLANK[[32, *range(9, 14)]] = True


def word_hashes(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all words, one text after another, and how many words each text has.

    A-Z count as lower case; words are runs of anything but the blanks of ASCII.
    """
    raw = [t.encode("utf-8", "surrogatepass").translate(_LOWER) for t in texts]
    size = np.array([len(r) + 1 for r in raw], np.int64)
    codes = np.frombuffer(b" ".join(raw) + b" ", np.uint8)
    blank = _BLANK[codes]
    before = np.empty(len(codes), bool)
    before[0] = True
    before[1:] = blank[:-1]
    starts = np.flatnonzero(~blank & before)
    ends = np.flatnonzero(blank & ~before)
    hashes = span_hashes(codes, starts, ends) if len(starts) else np.empty(0, np.uint64)
    bounds = np.searchsorted(starts, np.concatenate([[0], np.cumsum(size)]))
    return hashes, np.diff(bounds)


def shingle_sets(texts: list[str], k: int) -> list[np.ndarray]:
    """The sorted distinct hashes of each text's k-word shingles (of the whole text, if it has fewer words)."""
    words, counts = word_hashes(texts)
    with np.errstate(over="ignore"):
        n = max(0, len(words) - k + 1)
        rolled = np.zeros(n, np.uint64)
        for j in range(k):
            rolled = rolled * np.uint64(0xD6E8FEB86659FD93) + words[j : j + n]
        rolled = mix64(rolled)
        out, at = [], 0
        for c in counts.tolist():
            if c >= k:
                own = np.sort(rolled[at : at + c - k + 1])
                keep = np.empty(len(own), bool)
                keep[0] = True
                np.not_equal(own[1:], own[:-1], out=keep[1:])
                out.append(own[keep])
            elif c:
                h = np.uint64(c)
                for w in words[at : at + c]:
                    h = mix64((h ^ w) * np.uint64(0xA0761D6478BD642F))
                out.append(np.array([h], np.uint64))
            else:
                out.append(np.empty(0, np.uint64))
            at += c
    return out
