"""Language identification: sparse multinomial logistic regression on TF-IDF character n-grams.

Features are hashed n-grams of one to three lower-cased characters; document frequencies are
counted over every document that may be learned from. Weights are fitted by follow-the-
regularised-leader with an elastic net, on a sample of at most about `Settings.sample` labelled
documents, and probabilities are calibrated by one temperature on a part of that sample.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import batch, sliced

UNKNOWN = "und"


@dataclass(frozen=True)
class Settings:
    bits: int = 15
    sample: int = 3000
    alpha: float = 0.5
    beta: float = 1.0
    l1: float = 1e-4
    l2: float = 1e-4
    epochs: int = 4
    calibration: float = 0.2
    piece: int = 1 << 20


@dataclass
class Model:
    languages: list[str] = field(default_factory=list)
    idf: np.ndarray | None = None
    weights: np.ndarray | None = None
    bias: np.ndarray | None = None
    temperature: float = 1.0


def has_letter(text: str) -> bool:
    return any(map(str.isalpha, text))


def term_counts(text: str, settings: Settings) -> tuple[np.ndarray, np.ndarray]:
    """Feature indices and their counts; long texts go through in overlapping pieces."""
    size = 1 << settings.bits
    total = np.zeros(size, np.int64)
    shift = np.uint32(32 - settings.bits)
    for at in range(0, max(1, len(text)), settings.piece):
        part = text[max(0, at - 2) : at + settings.piece].lower()
        c = np.frombuffer(part.encode("utf-32-le", "surrogatepass"), np.uint32)
        head = min(at, 2)  # n-grams that end in these belong to the piece before
        one = c * np.uint32(0x9E3779B1)
        total += np.bincount((one[head:] + np.uint32(0x3C6EF372)) >> shift, minlength=size)
        if len(c) > 1:
            two = one[1:] + c[:-1] * np.uint32(0x85EBCA77)
            total += np.bincount((two[max(0, head - 1) :] * np.uint32(0x27D4EB2F)) >> shift, minlength=size)
        if len(c) > 2:
            three = two[1:] + c[:-2] * np.uint32(0xC2B2AE3D)
            total += np.bincount((three * np.uint32(0x165667B1)) >> shift, minlength=size)
    at = total.nonzero()[0]
    return at, total[at]


def vector(at: np.ndarray, counts: np.ndarray, idf: np.ndarray) -> np.ndarray:
    x = (1 + np.log(counts)) * idf[at]
    norm = np.sqrt(x @ x)
    return x / norm if norm > 0 else x


def may_learn(doc_id: Column) -> Column:
    """crc32 of the id's text modulo 3 is not 1."""
    return F.crc32(doc_id.cast("string")) % 3 != 1


def document_frequencies(texts: DataFrame, settings: Settings) -> tuple[np.ndarray, int]:
    """In how many texts each feature occurs, summed within each task first."""
    schema = pa.schema([("term", pa.int32()), ("n", pa.int64())])

    def count(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen, docs = np.zeros(1 << settings.bits, np.int64), 0
        for got in sliced(it):
            for text in got.column(0).to_pylist():
                seen[term_counts(text, settings)[0]] += 1
                docs += 1
        at = seen.nonzero()[0]
        yield batch(schema, np.append(at, -1).astype(np.int32), np.append(seen[at], docs))

    rows = texts.mapInArrow(count, "term int, n bigint").groupBy("term").agg(F.sum("n").alias("n")).collect()
    df = np.zeros(1 << settings.bits, np.int64)
    docs = 0
    for r in rows:  # one for each feature at most
        if r.term < 0:
            docs = r.n
        else:
            df[r.term] = r.n
    return df, docs


def sample_vectors(labelled: DataFrame, settings: Settings) -> list:
    """(doc_id, lang, feature indices, counts) of a hash sample with equal shares of each language."""
    per = labelled.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).orderBy("lang").collect()  # one row for each language
    if not per:
        return []
    quota = max(1.0, settings.sample / len(per))
    unit = F.pmod(F.xxhash64(F.col("doc_id")), F.lit(1 << 30)) / float(1 << 30)
    share = F.create_map(*(F.lit(v) for r in per for v in (r.lang, min(1.0, quota / r.n))))
    keep = unit < F.try_element_at(share, F.col("lang"))
    kinds = pa.schema([("doc_id", pa.int64()), ("lang", pa.string()), ("at", pa.list_(pa.int32())), ("counts", pa.list_(pa.int32()))])

    def features(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for got in sliced(it):
            pairs = [term_counts(t, settings) for t in got.column(2).to_pylist()]
            yield batch(kinds, got.column(0), got.column(1), [p[0].astype(np.int32) for p in pairs], [np.minimum(p[1], 2**31 - 1).astype(np.int32) for p in pairs])

    rows = labelled.where(keep).select("doc_id", "lang", "text").mapInArrow(features, "doc_id bigint, lang string, at array<int>, counts array<int>")
    table = rows.toArrow().combine_chunks()
    order = sorted(range(table.num_rows), key=lambda k: (zlib.crc32(str(table["doc_id"][k].as_py()).encode()), table["doc_id"][k].as_py(), table["lang"][k].as_py()))
    return [(table["lang"][k].as_py(), table["at"][k].values.to_numpy(), table["counts"][k].values.to_numpy()) for k in order]


def fit_weights(data: list, n_classes: int, size: int, s: Settings) -> tuple[np.ndarray, np.ndarray]:
    """Follow-the-regularised-leader with per-coordinate rates; data: (class, indices, values)."""
    z, n = np.zeros((size + 1, n_classes)), np.zeros((size + 1, n_classes))  # the last row is the bias

    def current(at: np.ndarray) -> np.ndarray:
        zz, nn = z[at], n[at]
        w = -(zz - np.sign(zz) * s.l1) / ((s.beta + np.sqrt(nn)) / s.alpha + s.l2)
        w[np.abs(zz) <= s.l1] = 0
        return w

    for _ in range(s.epochs):
        for label, at, x in data:
            rows, values = np.append(at, size), np.append(x, 1.0)
            w = current(rows)
            p = softmax(values @ w)
            p[label] -= 1
            g = values[:, None] * p
            grown = n[rows] + g * g
            z[rows] += g - (np.sqrt(grown) - np.sqrt(n[rows])) / s.alpha * w
            n[rows] = grown
    w = current(np.arange(size + 1))
    return w[:-1], w[-1]


def softmax(logits: np.ndarray) -> np.ndarray:
    e = np.exp(logits - logits.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


def fit_temperature(logits: np.ndarray, labels: np.ndarray) -> float:
    """The temperature with the least negative log-likelihood, by golden-section search on its logarithm."""
    if not len(labels):
        return 1.0

    def loss(t: float) -> float:
        return -np.log(np.maximum(softmax(logits / np.exp(t))[np.arange(len(labels)), labels], 1e-300)).mean()

    lo, hi, ratio = np.log(0.05), np.log(20.0), (np.sqrt(5) - 1) / 2
    for _ in range(60):
        a, b = hi - ratio * (hi - lo), lo + ratio * (hi - lo)
        lo, hi = (lo, b) if loss(a) <= loss(b) else (a, hi)
    return float(np.exp((lo + hi) / 2))


def train(docs: DataFrame, settings: Settings = Settings()) -> Model:
    """A model from the documents that may_learn() allows and that have a label and a text."""
    labelled = docs.where(may_learn(F.col("doc_id")) & F.col("lang").isNotNull() & F.col("text").isNotNull()).select(F.col("doc_id").cast("bigint").alias("doc_id"), "lang", "text")
    rows = sample_vectors(labelled, settings)
    if not rows:
        return Model()
    df, n_docs = document_frequencies(labelled.select("text"), settings)
    idf = np.log((1 + n_docs) / (1 + df)) + 1
    languages = sorted({r[0] for r in rows})
    index = {lang: k for k, lang in enumerate(languages)}
    data = [(index[lang], at, vector(at, counts, idf)) for lang, at, counts in rows]
    held = int(len(data) * settings.calibration)
    w, b = fit_weights(data[held:], len(languages), 1 << settings.bits, settings)
    logits = np.array([x @ w[at] + b for _, at, x in data[:held]]).reshape(held, len(languages))
    return Model(languages, idf, w, b, fit_temperature(logits, np.array([d[0] for d in data[:held]], np.int64)))


def predict_batches(it: Iterator[pa.RecordBatch], model: Model, settings: Settings) -> Iterator[pa.RecordBatch]:
    schema = pa.schema([("doc_id", pa.int64()), ("lang_pred", pa.string()), ("score", pa.float64())])
    for got in sliced(it):
        names, scores = [], []
        for text in got.column(1).to_pylist():
            if not model.languages or not text or not has_letter(text):
                names.append(UNKNOWN)
                scores.append(0.0)
                continue
            at, counts = term_counts(text, settings)
            p = softmax((vector(at, counts, model.idf) @ model.weights[at] + model.bias) / model.temperature)
            best = int(p.argmax())
            names.append(model.languages[best])
            scores.append(float(min(1.0, p[best])))
        yield batch(schema, got.column(0), names, scores)


def predict(docs: DataFrame, model: Model, settings: Settings = Settings()) -> DataFrame:
    """doc_id, held_out, lang_pred, score of every row of docs (doc_id, text, lang).

    Without a letter in the text, or without anything to learn from: `und` with score 0. A null
    doc_id counts as one that may not be held out. Repeated rows each give a row; extra columns
    are ignored. Weights have a column of 2**bits numbers for each label value among the rows learned
    from, which `sample` bounds.
    """
    spark = docs.sparkSession
    held = spark.sparkContext.broadcast(model)
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text")
    out = rows.mapInArrow(lambda it: predict_batches(it, held.value, settings), T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())]))
    return out.select("doc_id", F.coalesce(~may_learn(F.col("doc_id")), F.lit(False)).alias("held_out"), "lang_pred", "score")


def identify(docs: DataFrame, settings: Settings = Settings()) -> DataFrame:
    return predict(docs, train(docs, settings), settings)


def keep_identified(docs: DataFrame, least: float = 0.5, settings: Settings = Settings()) -> DataFrame:
    """The pipeline's filter: documents whose language is known with at least that probability.

    `lang` becomes the predicted one; columns and their order stay.
    """
    model = docs.sparkSession.sparkContext.broadcast(train(docs, settings))
    names = docs.columns
    kinds = docs.schema

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at_text, at_lang = names.index("text"), names.index("lang")
        for got in sliced(it):
            pair = pa.RecordBatch.from_arrays([pa.array([0] * got.num_rows, pa.int64()), got.column(at_text)], names=["doc_id", "text"])
            for said in predict_batches(iter([pair]), model.value, settings):
                keep = np.array([n != UNKNOWN for n in said.column(1).to_pylist()], bool) & (said.column(2).to_numpy(zero_copy_only=False) >= least)
                columns = [said.column(1) if k == at_lang else c for k, c in enumerate(got.columns)]
                yield pa.RecordBatch.from_arrays(columns, names=got.schema.names).filter(pa.array(keep))

    return docs.mapInArrow(run, kinds)
