"""Query op4: personal data in every document."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .common import load
from .pii import personal_data


def op4_weak_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return personal_data(load(spark, sf_dir, "documents"))
