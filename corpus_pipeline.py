"""A cleaning pipeline over documents: language, lines, near-duplicates, personal data, packing.

Each stage is a function (spark, docs, sf_dir) -> DataFrame; its result is written as Parquet
and read again as the next one's docs. All stages but the last keep the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from tissuebalance.llm.common import Workspace, load
from tissuebalance.llm.language import keep_identified
from tissuebalance.llm.lines import without_repeated_lines
from tissuebalance.llm.minhash import Settings, near_duplicates
from tissuebalance.llm.op2_packing import library_encoder
from tissuebalance.llm.packing import pack
from tissuebalance.llm.pii import masked


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language is recognised; lang is the recognised one."""
    return keep_identified(docs)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that repeat an earlier line go, from five words on up to one word; documents stay."""
    return without_repeated_lines(docs)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest id of each group stays (five words, similarity 0.8)."""
    found = near_duplicates(docs, Settings())
    gone = found.where(~F.col("kept") & F.col("doc_id").isNotNull()).select(F.col("doc_id").alias("_gone")).distinct()
    return docs.join(gone, docs["doc_id"].cast("bigint") == gone["_gone"], "left_anti")


def personal(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data in texts becomes its kind in brackets."""
    return masked(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of token sequences of at most 1024 ids."""
    return pack(docs, library_encoder)


STAGES = [("language", language), ("lines", lines), ("near_copies", near_copies), ("personal", personal), ("packing", packing)]

#: Classifiers and tokenizers are not expressible in SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    space = Workspace(spark, "pipeline")
    docs = load(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = space.write(docs, name)
    return docs
