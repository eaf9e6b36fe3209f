"""Near-duplicate lines by a deletion-neighbourhood join.

Lines are compared as word sequences. Any line that is not blank goes where an earlier one has
equal words; lines of at least `least` words also where an earlier one is within the edit bound, one
word inserted, deleted or replaced. Equal sequences meet first and only the earliest goes on. A line
can only have a neighbour if another line shares its first or its last half (one edit leaves
one half whole, counted on the shorter line), so only such lines emit their neighbourhood:

* the hash of the line without word i, together with i, for every i, and
* the hash of the whole line together with every place where a word may stand in another one.

All lines that meet under one key are within the bound of one another, so the earliest of each
key is all that is needed: keys are reduced to it before anything is joined, and no pairs of a
group are ever made. The edit distance to that earliest line is then verified on the words.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Workspace, batch, chunks, mix64, powers, sliced, span_hashes

_BLANK = np.zeros(256, bool)
_BLANK[[9, 11, 12, 13, 32]] = True
LAST = (1 << 63) - 1


def line_words(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Word hashes of joined texts; first word, number of words and text of each line."""
    raw = [t.encode("utf-8", "surrogatepass") for t in texts]
    codes = np.frombuffer(b"\n".join(raw) + b"\n", np.uint8)
    stop = codes == 10
    blank = _BLANK[codes] | stop
    before = np.empty(len(codes), bool)
    before[0] = True
    before[1:] = blank[:-1]
    starts, ends = np.flatnonzero(~blank & before), np.flatnonzero(blank & ~before)
    words = span_hashes(codes, starts, ends) if len(starts) else np.empty(0, np.uint64)
    closes = np.flatnonzero(stop)
    upto = np.searchsorted(starts, closes)
    first = np.concatenate([[0], upto[:-1]])
    text_end = np.cumsum([len(r) + 1 for r in raw]) - 1
    return words, first, upto - first, np.searchsorted(text_end, closes)


def sums(words: np.ndarray) -> np.ndarray:
    up, _ = powers(len(words) + 1)
    out = np.empty(len(words) + 1, np.uint64)
    out[0] = 0
    np.cumsum(words * up[: len(words)], out=out[1:])
    return out


def ranges(total: np.ndarray, a: np.ndarray, b: np.ndarray, salt: int) -> np.ndarray:
    """Hashes of the word ranges a..b, told apart by their length and the salt."""
    _, down = powers(len(total) + 1)
    return mix64((total[b] - total[a]) * down[a] + (b - a).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(salt))


LINES = "doc bigint, version bigint, line int, key_a bigint, key_b bigint, halves array<bigint>"
LINES_ARROW = pa.schema([("doc", pa.int64()), ("version", pa.int64()), ("line", pa.int32()), ("key_a", pa.int64()), ("key_b", pa.int64()), ("halves", pa.list_(pa.int64()))])


def scan(it: Iterator[pa.RecordBatch], least: int, piece: int) -> Iterator[pa.RecordBatch]:
    for got in sliced(it):
        docs, versions, texts = (got.column(0).to_numpy(), got.column(1).to_numpy(), got.column(2).to_pylist())
        for lo, hi in chunks(texts, piece):
            words, first, count, text = line_words(texts[lo:hi])
            begin = np.searchsorted(text, np.arange(hi - lo))
            number = np.arange(len(first)) - begin[text]
            keep = np.flatnonzero(count >= 1)
            a, n = first[keep], count[keep]
            b = a + n
            long = n >= least
            one, two = sums(words), sums(mix64(words ^ np.uint64(0x5851F42D4C957F2D)))
            x, y, h = a[long], b[long], n[long]
            halves = np.stack([ranges(one, x, x + h // 2, 1), ranges(one, x, x + (h - 1) // 2, 1), ranges(one, y - h // 2, y, 2), ranges(one, y - (h - 1) // 2, y, 2)], axis=1)
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(4 * long)]).astype(np.int32)), pa.array(halves.view(np.int64).ravel()))
            yield batch(LINES_ARROW, docs[lo:hi][text[keep]], versions[lo:hi][text[keep]], number[keep].astype(np.int32), ranges(one, a, b, 3).view(np.int64), ranges(two, a, b, 4).view(np.int64), lists)


WORDS_ARROW = pa.schema([("key_a", pa.int64()), ("key_b", pa.int64()), ("doc", pa.int64()), ("version", pa.int64()), ("line", pa.int32()), ("words", pa.binary())])


def pick(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The word hashes of the wanted lines of each document."""
    for got in sliced(it):
        out: list[list] = [[] for _ in range(6)]
        rows = zip(*(got.column(n).to_pylist() for n in ("doc", "version", "text", "wanted")), strict=True)
        for doc, version, text, wanted in rows:
            words, first, count, _ = line_words([text])
            for w in wanted:
                k = w["line"]
                for c, v in zip(out, (w["key_a"], w["key_b"], doc, version, k, words[first[k] : first[k] + count[k]].tobytes()), strict=True):
                    c.append(v)
        yield batch(WORDS_ARROW, *out)


def neighbourhood(words: np.ndarray) -> np.ndarray:
    """Keys of all variants within one deletion, and of the line as such a variant of a longer one."""
    n = len(words)
    up, down = powers(n + 2)
    total = sums(words)
    at = np.arange(n)
    less = total[:-1] + (total[n] - total[1:]) * down[1]
    place = np.uint64(0xA24BAED4963EE407)
    own = mix64(mix64(less + np.uint64(n - 1)) ^ (at.astype(np.uint64) + np.uint64(1)) * place)
    whole = mix64(mix64(total[n : n + 1] + np.uint64(n)) ^ (np.arange(n + 1).astype(np.uint64) + np.uint64(1)) * place)
    return np.concatenate([own, whole])


def emit(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    schema = pa.schema([("variant", pa.int64()), ("doc", pa.int64()), ("version", pa.int64()), ("line", pa.int32())])
    for got in it:
        for k in range(0, got.num_rows, 2000):
            part = got.slice(k, 2000)
            keys = [neighbourhood(np.frombuffer(w, np.uint64)) for w in part.column("words").to_pylist()]
            n = [len(x) for x in keys]
            if n:
                yield batch(schema, np.concatenate(keys).view(np.int64), *(np.repeat(part.column(c).to_numpy(), n) for c in ("doc", "version", "line")))


def within_one(a: np.ndarray, b: np.ndarray) -> bool:
    """Whether one inserted, deleted or replaced word at most turns a into b."""
    if len(a) > len(b):
        a, b = b, a
    if len(b) - len(a) > 1:
        return False
    differ = np.flatnonzero(a != b[: len(a)])
    if not len(differ):
        return True
    k = differ[0]
    return bool(np.array_equal(a[k + 1 :], b[k + 1 :]) if len(a) == len(b) else np.array_equal(a[k:], b[k + 1 :]))


def verify(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for got in it:
        keep = [within_one(np.frombuffer(a, np.uint64), np.frombuffer(b, np.uint64)) for a, b in zip(got.column("words").to_pylist(), got.column("other").to_pylist(), strict=True)]
        yield batch(pa.schema([(n, got.schema.field(n).type) for n in ("doc", "version", "line")]), *(got.column(n) for n in ("doc", "version", "line"))).filter(pa.array(keep, pa.bool_()))


def dropped_lines(rows: DataFrame, space: Workspace, least: int, piece: int = 1 << 20) -> DataFrame:
    """doc, version, line, near of each line to drop; rows: doc, version, text."""
    lines = space.write(rows.mapInArrow(lambda it: scan(it, least, piece), LINES), "lines")
    place = F.struct("doc", "version", "line")
    distinct = space.write(lines.groupBy("key_a", "key_b").agg(F.min(place).alias("first"), F.count(F.lit(1)).alias("n"), F.first("halves").alias("halves")), "distinct")
    again = distinct.where("n > 1").select("key_a", "key_b", "first")
    exact = lines.join(again, ["key_a", "key_b"]).where(place != F.col("first")).select("doc", "version", "line", F.lit(False).alias("near"))
    keyed = distinct.select("key_a", "key_b", "first", F.explode(F.array_distinct("halves")).alias("half"))
    shared = keyed.groupBy("half").agg(F.min(F.struct("key_a", "key_b")).alias("least"), F.max(F.struct("key_a", "key_b")).alias("most")).where("least <> most").select("half")
    able = keyed.join(shared, "half", "left_semi").select("key_a", "key_b", "first").distinct()
    wanted = able.groupBy(F.col("first.doc").alias("doc"), F.col("first.version").alias("version")).agg(F.collect_list(F.struct("key_a", "key_b", F.col("first.line").alias("line"))).alias("wanted"))
    words = space.write(rows.join(wanted, ["doc", "version"]).mapInArrow(pick, "key_a bigint, key_b bigint, doc bigint, version bigint, line int, words binary").dropDuplicates(["key_a", "key_b"]), "words")
    variants = words.select("doc", "version", "line", "words").mapInArrow(emit, "variant bigint, doc bigint, version bigint, line int")
    earliest = variants.groupBy("variant").agg(F.min(place).alias("first"), F.max(place).alias("last")).where("first <> last").select("variant", "first")
    best = variants.join(earliest, "variant").where(place != F.col("first")).groupBy("doc", "version", "line").agg(F.min("first").alias("first"))
    other = words.select(*(F.col(c).alias(f"first_{c}") for c in ("doc", "version", "line")), F.col("words").alias("other"))
    pairs = best.select("doc", "version", "line", *(F.col(f"first.{c}").alias(f"first_{c}") for c in ("doc", "version", "line")))
    pairs = pairs.join(words.select("doc", "version", "line", "words"), ["doc", "version", "line"]).join(other, ["first_doc", "first_version", "first_line"])
    near = pairs.select("doc", "version", "line", "words", "other").mapInArrow(verify, "doc bigint, version bigint, line int").withColumn("near", F.lit(True))
    gone = space.write(exact.unionByName(near), "gone")
    for done in (lines, distinct, words):
        space.drop(done)
    return gone


def keyed_rows(docs: DataFrame, *columns: str) -> DataFrame:
    """doc, version and text of each row: the id (null last) and a hash that tells texts of one id apart."""
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(F.coalesce(F.col("doc_id").cast("bigint"), F.lit(LAST)).alias("doc"), F.xxhash64(text).alias("version"), text.alias("text"), *columns)


def dedupe_lines(docs: DataFrame, least: int = 5) -> DataFrame:
    """doc_id, n_lines, n_exact, n_near, text (what stays) of every row of docs (doc_id, text).

    A line goes if an earlier one (smaller doc_id, then line) has the same words, and one of at
    least `least` words also if an earlier one of that length is within one word of it. All
    comparisons are on the input. Blank lines stay.
    Null texts count as empty and have one empty line. Rows with equal id and text are one
    document; null ids come last; extra columns are ignored.
    """
    space = Workspace(docs.sparkSession, "lines")
    rows = keyed_rows(docs, F.col("doc_id").cast("bigint").alias("doc_id"))
    gone = dropped_lines(rows.select("doc", "version", "text"), space, least)
    gone = gone.groupBy("doc", "version").agg(F.collect_list(F.struct("line", "near")).alias("gone"))
    schema = pa.schema([("doc_id", pa.int64()), ("n_lines", pa.int64()), ("n_exact", pa.int64()), ("n_near", pa.int64()), ("text", pa.string())])

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for got in sliced(it):
            counts: list[list[int]] = [[], [], []]
            kept = []
            for text, drop in zip(got.column("text").to_pylist(), got.column("gone").to_pylist(), strict=True):
                lines, drop = text.split("\n"), {d["line"]: d["near"] for d in drop or ()}
                near = sum(drop.values())
                for c, v in zip(counts, (len(lines), len(drop) - near, near), strict=True):
                    c.append(v)
                kept.append("\n".join(x for k, x in enumerate(lines) if k not in drop) if drop else text)
            yield batch(schema, got.column("doc_id"), *counts, kept)

    return rows.join(gone, ["doc", "version"], "left").select("doc_id", "text", "gone").mapInArrow(run, "doc_id bigint, n_lines bigint, n_exact bigint, n_near bigint, text string")


def without_repeated_lines(docs: DataFrame, least: int = 5) -> DataFrame:
    """The pipeline's stage: the same columns with repeated lines taken out of text; n_chars follows. Rules as in dedupe_lines."""
    space = Workspace(docs.sparkSession, "lines")
    gone = dropped_lines(keyed_rows(docs), space, least).groupBy("doc", "version").agg(F.collect_set("line").alias("gone"))
    names, kinds = docs.columns, docs.schema
    whole = F.struct(*(F.col(f"`{n}`") for n in names)).alias("row")
    keys = docs.select(whole, F.coalesce(F.col("doc_id").cast("bigint"), F.lit(LAST)).alias("doc"), F.xxhash64(F.coalesce(F.col("text"), F.lit(""))).alias("version"))

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for got in sliced(it):
            columns = dict(zip(names, got.column("row").flatten(), strict=True))
            texts = columns["text"].to_pylist()
            for k, drop in enumerate(got.column("gone").to_pylist()):
                if drop and texts[k] is not None:
                    drop = set(drop)
                    texts[k] = "\n".join(x for j, x in enumerate(texts[k].split("\n")) if j not in drop)
            columns["text"] = pa.array(texts, columns["text"].type)
            if "n_chars" in columns:
                columns["n_chars"] = pa.array([None if t is None else len(t) for t in texts], columns["n_chars"].type)
            yield pa.RecordBatch.from_arrays([columns[n] for n in names], names=names)

    return keys.join(gone, ["doc", "version"], "left").select("row", "gone").mapInArrow(run, kinds)


def digest_rows(found: DataFrame) -> DataFrame:
    return found.select("doc_id", "n_lines", "n_exact", "n_near", F.sha2(F.col("text").cast("binary"), 256).alias("kept_sha256"))
