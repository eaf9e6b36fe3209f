"""License scans by conditional compression.

The words around each mention of licensing, as far as the longest statement may reach, are aligned
exactly with every statement of every template, whatever the line breaks. Statements that are
found to a sufficient share are candidates. Each candidate's block is compressed alone and with
its template's wording as a raw dictionary of zstandard, and candidates are ranked by the bytes
saved. The first of the ranking wins its words; of those that save as much to within a few bytes,
and of other alignments of the same statement, the one whose wording differs least. What is left beside it is searched again.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch
from .license_texts import TEMPLATES

_GAP = "[^A-Za-z0-9]+"
MENTION = rf"(?i)licen[sc]e|copyright|spdx|all{_GAP}rights{_GAP}reserved|public{_GAP}domain|creative{_GAP}commons|permission{_GAP}(?:is{_GAP}hereby|to{_GAP}use)|redistribut|\bCC{_GAP}(?:BY|0)|\bCC0\b"
_MENTION = re.compile(MENTION)
_WORD = re.compile(r"[a-z0-9]+(?:\.[0-9]+)*")
_ONE = 1 << 32
#: Bytes by which compressed sizes differ for reasons other than the wording.
NOISE = 4
#: The compressor looks for no matches in the last bytes, so these are not the block's own.
TAIL = b"\n" * 16


def words(text: str) -> list[str]:
    return _WORD.findall(text.lower())


def alignments(statement: np.ndarray, text: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ends in text, starts and scores of the best alignments: statement words found in order less words put between."""
    at = np.arange(len(text) + 1)
    fall, best = at * _ONE, at
    for w in statement:
        more = best.copy()
        np.maximum(more[1:], np.where(text == w, best[:-1] + _ONE, 0), out=more[1:])
        best = np.maximum(np.maximum.accumulate(more + fall) - fall, at)
    ends = np.flatnonzero(best[1:] > best[:-1] - _ONE) + 1
    return ends, best[ends] & (_ONE - 1), best[ends] >> 32


def differences(statement: list[str], found: list[str]) -> tuple[list[str], list[str]]:
    """The statement's words that are missing in found, and the words put between, by one best alignment."""
    n, m = len(statement), len(found)
    common = [[0] * (m + 1) for _ in range(n + 1)]
    for i in range(n - 1, -1, -1):
        for j in range(m - 1, -1, -1):
            common[i][j] = 1 + common[i + 1][j + 1] if statement[i] == found[j] else max(common[i + 1][j], common[i][j + 1])
    missing, extra, i, j = [], [], 0, 0
    while i < n or j < m:
        if i < n and j < m and statement[i] == found[j]:
            i, j = i + 1, j + 1
        elif i < n and (j == m or common[i + 1][j] >= common[i][j + 1]):
            missing.append(statement[i])
            i += 1
        else:
            extra.append(found[j])
            j += 1
    return missing, extra


class Scanner:
    def __init__(self, templates: dict[str, list[str]], least: float, level: int = 3) -> None:
        self.least, self.plain = least, zstandard.ZstdCompressor(level=level, write_content_size=False)
        self.given = {name: zstandard.ZstdCompressor(level=level, write_content_size=False, write_dict_id=False, dict_data=zstandard.ZstdCompressionDict("\n".join(" ".join(words(x)) for x in s).encode(), dict_type=zstandard.DICT_TYPE_RAWCONTENT)) for name, s in templates.items()}
        self.statements = [(name, words(s)) for name, statements in templates.items() for s in statements]
        self.number: dict[str, int] = {}
        self.coded = [np.array([self.number.setdefault(w, len(self.number)) for w in s]) for _, s in self.statements]
        self.reach = int(max(len(s) for _, s in self.statements) * (2 - least)) + 1

    def saved(self, block: str, name: str) -> tuple[int, float]:
        """Bytes of the block's compressed size that a template saves, and their share."""
        raw = block.encode("utf-8", "surrogatepass") + TAIL
        alone = len(self.plain.compress(raw))
        less = alone - len(self.given[name].compress(raw))
        return less, less / alone

    def candidates(self, codes: np.ndarray) -> list[tuple[int, int, int, float]]:
        """(start, end, statement, share) of all statements found to a sufficient share in a text's words."""
        seen, out = set(codes.tolist()), []
        for k, coded in enumerate(self.coded):
            if sum(w in seen for w in coded.tolist()) >= self.least * len(coded):
                for end, start, score in zip(*(x.tolist() for x in alignments(coded, codes)), strict=True):
                    if score / len(coded) >= self.least:
                        out.append((start, end, k, score / len(coded)))
        return out

    def confirmed(self, codes: np.ndarray, block) -> list[tuple[int, int, int]]:
        """(start, end, statement) of the winners in a text's words; block(start, end) is what stands there."""
        out, todo = [], [(0, len(codes))]
        while todo:
            lo, hi = todo.pop()
            able = []
            for start, end, k, share in self.candidates(codes[lo:hi]):
                name = self.statements[k][0]
                able.append((self.saved(block(lo + start, lo + end), name)[0], share, name, lo + start, lo + end, k))
            taken: list[tuple[int, int]] = []
            while able:
                most = max(able)
                rivals = [c for c in able if (c[0] >= most[0] - NOISE or c[5] == most[5]) and c[3] < most[4] and most[3] < c[4]]
                _, _, _, a, b, k = min(rivals, key=lambda c: (-c[1], -c[0], c[3] - c[4], c[2:]))
                taken.append((a, b))
                out.append((a, b, k))
                able = [c for c in able if c[4] <= a or b <= c[3]]
            if taken:
                taken = [(lo, lo), *sorted(taken), (hi, hi)]
                todo += [(b, c) for (_, b), (c, _) in zip(taken, taken[1:], strict=False) if b < c]
        return sorted(out)

    def scan(self, text: str) -> list[tuple[int, int, str | None, float, list[str], list[str]]]:
        """First line, number of lines, license, gain, missing and extra words of each confirmed statement, and
        of each run of other lines that mention licensing (license None, the best gain)."""
        low, lines = text.lower(), text.split("\n")
        stops = np.array([k for k, c in enumerate(low) if c == "\n"], np.int64)
        found = list(_WORD.finditer(low))
        mentions = [m.span() for m in _MENTION.finditer(low)]
        begin = np.array([m.start() for m in found], np.int64)
        line = np.searchsorted(stops, begin)
        own = [m.group() for m in found]
        codes = np.array([self.number.get(w, -1) for w in own], np.int64)
        regions: list[list[int]] = []
        for a, b in mentions:
            a, b = max(0, int(np.searchsorted(begin, a, "right")) - 1 - self.reach), min(len(own), int(np.searchsorted(begin, b)) + self.reach)
            if regions and a <= regions[-1][1]:
                regions[-1][1] = b
            else:
                regions.append([a, b])

        def block(a: int, b: int) -> str:
            return " ".join(own[a:b])  # line breaks and comment marks are no part of the wording

        out, covered = [], set()
        for lo, hi in regions:
            for a, b, k in self.confirmed(codes[lo:hi], lambda a, b: block(lo + a, lo + b)):  # noqa: B023
                name, statement = self.statements[k]
                first, last = int(line[lo + a]), int(line[lo + b - 1])
                covered.update(range(first, last + 1))
                out.append((first, last - first + 1, name, self.saved(block(lo + a, lo + b), name)[1], *differences(statement, own[lo + a : lo + b])))
        rest = sorted({k for a, b in mentions for k in range(*(int(x) for x in (np.searchsorted(stops, a), np.searchsorted(stops, b - 1) + 1)))} - covered)
        for k, x in enumerate(rest):
            if not k or rest[k - 1] + 1 < x:
                n = next(i for i in range(1, len(rest) - k + 1) if k + i == len(rest) or rest[k + i] > x + i)
                rest_words = " ".join(words("\n".join(lines[x : x + n]))) or " "
                out.append((x, n, None, max(self.saved(rest_words, name)[1] for name in self.given), [], []))
        return sorted(out, key=lambda r: r[0])


SCHEMA = "doc_id bigint, line bigint, n_lines bigint, license string, gain double, missing string, extra string"


def scan_licenses(docs: DataFrame, least: float = 0.8) -> DataFrame:
    """One row for each license statement in docs (doc_id, text): where it stands, its license, the
    size saved, and the words missing from or put into the statement. Lines that mention licensing
    beside all confirmed statements give rows with a null license.

    Null and empty texts have no rows. Repeated rows each give their rows, extra columns are
    ignored, an empty table gives none. Whole texts are searched, however long.
    """
    kinds = pa.schema([("doc_id", pa.int64()), ("line", pa.int64()), ("n_lines", pa.int64()), ("license", pa.string()), ("gain", pa.float64()), ("missing", pa.string()), ("extra", pa.string())])

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(TEMPLATES, least)
        for got in it:
            out: list[tuple] = []
            for doc, text in zip(got.column(0).to_pylist(), got.column(1).to_pylist(), strict=True):
                for line, n_lines, name, gain, missing, extra in scanner.scan(text):
                    out.append((doc, line, n_lines, name, round(gain, 6), " ".join(missing), " ".join(extra)))
            yield batch(kinds, *(zip(*out, strict=True) if out else [[]] * 7))

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").where(F.col("text").rlike(MENTION)).mapInArrow(run, SCHEMA)
