"""Query op8: license statements in all documents."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .common import load
from .licenses import scan_licenses


def op8_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(load(spark, sf_dir, "documents"))
