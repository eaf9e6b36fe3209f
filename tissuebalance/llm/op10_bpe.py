"""Query op10: encode every text with a public byte-level BPE vocabulary and decode it again."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pyarrow as pa
import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bpe import PIECE, Decoder, Encoder, Vocabulary
from .common import batch, load, sliced, text_or_empty

SCHEMA = "doc_id bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string"
_HELD: dict[str, tuple[Vocabulary, Encoder]] = {}


def encoder(path: str) -> Encoder:
    """One encoder for each worker process and vocabulary file; it only holds what is derived from the file."""
    if path not in _HELD:
        vocabulary = Vocabulary(path)
        _HELD[path] = vocabulary, Encoder(vocabulary)
    return _HELD[path][1]


def digests(batches: Iterator[pa.RecordBatch], path: str) -> Iterator[pa.RecordBatch]:
    schema = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())])
    machine = encoder(path)
    for got in sliced(batches):
        counts, ids_digest, text_digest = [], [], []
        for ids in machine.encode(got.column(1).to_pylist()):
            counts.append(len(ids))
            ids_digest.append(hashlib.sha256(ids.astype("<u4").tobytes()).hexdigest())
            decoder, seen = Decoder(machine.v), hashlib.sha256()
            for k in range(0, len(ids), PIECE):
                seen.update(decoder.feed(ids[k : k + PIECE]).encode("utf-8", "surrogatepass"))
            seen.update(decoder.finish().encode())
            text_digest.append(seen.hexdigest())
        yield batch(schema, got.column(0), counts, ids_digest, text_digest)


def encode_decode(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every row of docs (doc_id, text).

    A null text counts as empty: no ids, digests of nothing. Repeated rows each give a row,
    extra columns are ignored, an empty table gives an empty result. The special token's
    string becomes its id, as in the tokenizers library.
    """
    path = path or public_tokenizers.path("byte_bpe_50k.json")
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), text_or_empty().alias("text"))
    return rows.mapInArrow(lambda it: digests(it, path), SCHEMA)


def op10_bpe_encode_decode(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_decode(load(spark, sf_dir, "documents"))
