"""Tissues made from tables: elements with integer positions, owned by cells.

Every tissue has cell_id, element_no, x, y, z (whole numbers, so counts are exact on any
engine), cell_type and born. x is the partition axis.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def hundredths(name: str) -> Column:
    return F.round(F.col(name) * 100).cast("bigint")


def order_tissue(spark: SparkSession, folder: str) -> DataFrame:
    """Orders as cells, their lines as elements; x follows the order date, with no skew."""
    lines, orders, customers = (table(spark, folder, t) for t in ("lineitem", "orders", "customer"))
    rest = ["l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]
    owned = orders.join(customers, F.col("o_custkey") == F.col("c_custkey"))
    joined = lines.join(owned, F.col("l_orderkey") == F.col("o_orderkey"))  # last, so that lines are shuffled once, by the key of their window
    day = F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")).cast("bigint")
    return joined.select(
        F.col("l_orderkey").alias("cell_id"),
        F.row_number().over(Window.partitionBy("l_orderkey").orderBy(*rest)).alias("element_no"),
        (day * 1000 + (2 * F.col("l_quantity").cast("bigint") - 51) * 10).alias("x"),
        (F.expr("cast(round(o_totalprice * 100) as bigint) div 500") + hundredths("l_discount") * 100 - 500).alias("y"),
        (F.col("c_nationkey").cast("bigint") * 2000 + hundredths("l_tax") * 100 - 400).alias("z"),
        F.col("c_mktsegment").alias("cell_type"),
        F.col("l_shipdate").cast("date").alias("born"),
    )


def event_cloud(spark: SparkSession, folder: str) -> DataFrame:
    """Events as elements of a user's day; x follows a heavy-tailed value, the stress case."""
    ts = F.col("ts").cast("timestamp")
    return table(spark, folder, "events").select(
        (F.col("user_id") * 100 + F.dayofmonth("ts")).cast("bigint").alias("cell_id"),
        F.col("event_id").alias("element_no"),
        (hundredths("value") * 200).alias("x"),
        (F.col("user_id") * 1000).cast("bigint").alias("y"),
        F.expr("unix_micros(cast(ts as timestamp)) - 1704067200000000").alias("micros"),
        F.col("event_type").alias("cell_type"),
        ts.cast("date").alias("born"),
        F.get_json_object("props", "$.k").cast("bigint").alias("k"),
    ).withColumn("z", F.expr("micros div 3600000"))


def vector_cloud(spark: SparkSession, folder: str) -> DataFrame:
    """Embeddings as cells of one element, placed by their first three components."""
    part = [F.floor(F.get("embedding", F.lit(i)).cast("double") * 100000 + 0.5).cast("bigint") for i in range(3)]
    return table(spark, folder, "embeddings").select(F.col("vec_id").alias("cell_id"), F.lit(1).alias("element_no"), *(p.alias(n) for p, n in zip(part, "xyz", strict=True)), F.col("label").cast("string").alias("cell_type"), F.lit(None).cast("date").alias("born"))


def document_load(spark: SparkSession, folder: str) -> DataFrame:
    """Documents as slices of a one-dimensional load."""
    return table(spark, folder, "documents").select(F.col("doc_id").alias("slice_id"), F.col("n_chars").alias("work"))


TISSUES = {"order": order_tissue, "event": event_cloud, "vector": vector_cloud}
#: Cutoffs that keep the local density of each tissue bounded at the smaller scales.
DEFAULT_CUTOFF = {"order": 5000, "event": 20000, "vector": 10000}
