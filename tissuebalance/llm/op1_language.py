"""Query op1: the language of every document."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .common import load
from .language import identify


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return identify(load(spark, sf_dir, "documents"))
