"""Query op2: pack all documents into sequences of at most 1024 tokens."""

from __future__ import annotations

import base64

import numpy as np
import public_tokenizers
import tiktoken
from pyspark.sql import DataFrame, SparkSession

from .bpe import Encoder, Vocabulary
from .common import load
from .packing import pack

_HELD: dict[str, Encoder] = {}


def library_encoder() -> Encoder:
    """Ids of the 50k byte-level vocabulary; words not seen before go to a public BPE library."""
    path = public_tokenizers.path("byte_bpe_50k.json")
    if path not in _HELD:
        with open(public_tokenizers.path("byte_bpe_50k.tiktoken"), "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        core = tiktoken.Encoding("byte_bpe_50k", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})

        def words(unseen: list[str]) -> tuple[np.ndarray, np.ndarray]:
            ids = [core.encode_ordinary(w) for w in unseen]
            return np.array([i for w in ids for i in w], np.int64), np.array([len(w) for w in ids], np.int64)

        _HELD[path] = Encoder(Vocabulary(path), words)
    return _HELD[path]


def op2_nnls_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(load(spark, sf_dir, "documents"), library_encoder)
