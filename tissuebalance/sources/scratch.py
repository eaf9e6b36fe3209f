"""Folders for tables that outlive one job."""

from __future__ import annotations

import gc
import tempfile
import uuid

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, SparkSession


def scratch(spark: SparkSession, name: str) -> str:
    """A path in spark.checkpoint.dir, which driver and executors share.

    Only a plain local master may go without that setting; it then gets a temporary folder.
    """
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        folder = f"file://{tempfile.gettempdir()}/tissuebalance"
    return f"{folder}/{name}"


#: Written without checksum files and marker: each file that the driver or an executor makes on a local disk starts a
#: chmod, and a JVM that starts a process seems for a moment to hold its memory twice. Other stores read none of the fs options.
PLAIN = {"compression": "zstd", "fs.file.impl": "org.apache.hadoop.fs.RawLocalFileSystem", "fs.file.impl.disable.cache": "true", "mapreduce.fileoutputcommitter.marksuccessfuljobs": "false"}


def settled(df: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """The rows of df from a table of their own: made once, read often. Shuffle files that made them go. by: columns that part its files."""
    spark = df.sparkSession
    path = scratch(spark, f"held-{uuid.uuid4().hex}")
    (df.write.partitionBy(*by) if by else df.write).options(**PLAIN).parquet(path)
    release(spark)
    return spark.read.schema(df.schema).parquet(path)


def release(spark: SparkSession) -> None:
    """Have Spark delete the shuffle files of finished jobs, which it does once the driver's JVM finds their plans unreachable.

    Threads that tell listeners of a job's end hold its plan until they have something else to tell.
    """
    gc.collect()
    spark.range(0).count()
    sc = spark.sparkContext
    try:
        sc._jsc.sc().listenerBus().waitUntilEmpty(5000)
    except Py4JJavaError:
        return  # listeners are behind; the files go behind a later table
    sc._jvm.System.gc()
