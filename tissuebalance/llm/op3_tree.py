"""Query op3: the 20 nearest embeddings by inner product, through a k-means tree."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import load
from .tree import search
from .vectors import usable


def op3_kmeans_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "embeddings").where(usable()).select(F.col("vec_id").cast("bigint").alias("vec_id"), "embedding")
    queries = rows.where(F.col("vec_id") % 20 == 0).select(F.col("vec_id").alias("query_id"), "embedding")
    return search(rows, queries, 20)
