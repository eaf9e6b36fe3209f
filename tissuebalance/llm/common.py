"""Helpers shared by the operators of this subpackage."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from py4j.protocol import Py4JJavaError
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """A table of the input folder, read by Spark so that any file system works."""
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir.

    Only a plain local master may go without that setting; it then gets a temporary folder.
    """
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder
    master = spark.sparkContext.master
    if not master.startswith("local") or master.startswith("local-cluster"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    return f"file://{tempfile.gettempdir()}/tissuebalance"


#: Local files without checksum files: those two are made readable by a chmod for each, and a JVM that spawns a
#: process seems for a moment to hold its memory twice. Other file systems do not read these options.
PLAIN_FILES = {"fs.file.impl": "org.apache.hadoop.fs.RawLocalFileSystem", "fs.file.impl.disable.cache": "true"}


class Workspace:
    """Tables written to the shared folder to cut lineage; they survive lost executors."""

    def __init__(self, spark: SparkSession, label: str) -> None:
        self.spark = spark
        self.root = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
        self.count = 0

    def write(self, df: DataFrame, name: str) -> DataFrame:
        """The rows of df from a table of their own; shuffle files that made them go."""
        self.count += 1
        path = f"{self.root}/{self.count}-{name}"
        df.write.option("compression", "zstd").options(**PLAIN_FILES).parquet(path)
        self.release()
        return self.spark.read.schema(df.schema).parquet(path)

    def release(self) -> None:
        """Have Spark delete the shuffle files of finished jobs.

        It does so once the driver's JVM finds their plans unreachable. Threads that tell
        listeners of a job's end hold its plan until they have something else to tell.
        """
        sc = self.spark.sparkContext
        self.spark.range(0).count()
        try:
            sc._jsc.sc().listenerBus().waitUntilEmpty(5000)
        except Py4JJavaError:
            return  # listeners are behind; the files go behind a later table
        sc._jvm.System.gc()

    def drop(self, df: DataFrame) -> None:
        """Delete what write() returned, once nothing reads it any more."""
        jvm = self.spark.sparkContext._jvm
        for path in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
            if self.root.split("/")[-1] in path:
                target = jvm.org.apache.hadoop.fs.Path(path)
                target.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def tasks_for(spark: SparkSession, size: int, each: int) -> int:
    """How many tasks share `size` so that each gets about `each`, and none of the cores is idle."""
    return max(spark.sparkContext.defaultParallelism, -(-size // each))


def text_or_empty(column: str = "text") -> Column:
    return F.coalesce(F.col(column), F.lit(""))


def chunks(texts: list[str], limit: int) -> Iterator[tuple[int, int]]:
    """Ranges of texts with about `limit` characters each; one long text is a range of its own."""
    start, size = 0, 0
    for k, text in enumerate(texts):
        if size and size + len(text) > limit:
            yield start, k
            start, size = k, 0
        size += len(text)
    if start < len(texts):
        yield start, len(texts)


def mix64(h: np.ndarray) -> np.ndarray:
    """The finaliser of the public splitmix64 generator."""
    h = h ^ (h >> np.uint64(30))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(27)
    h *= np.uint64(0x94D049BB133111EB)
    h ^= h >> np.uint64(31)
    return h


_BASE = 0x9E3779B97F4A7C15 | 1
_POWERS: dict[str, np.ndarray] = {}


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first n powers of an odd base modulo 2**64, and those of its inverse."""
    if "up" not in _POWERS or len(_POWERS["up"]) < n:
        size = 1 << max(12, (n - 1).bit_length())
        with np.errstate(over="ignore"):
            for key, base in (("up", _BASE), ("down", pow(_BASE, -1, 1 << 64))):
                steps = np.full(size, np.uint64(base), np.uint64)
                steps[0] = 1
                _POWERS[key] = np.multiply.accumulate(steps)
    return _POWERS["up"], _POWERS["down"]


def span_hashes(codes: np.ndarray, starts: np.ndarray, ends: np.ndarray, block: int = 1 << 18) -> np.ndarray:
    """64-bit hashes of codes[starts[i]:ends[i]], equal for equal content wherever it stands. Works block by block."""
    if len(codes) > block and len(starts):
        if (starts[1:] < starts[:-1]).any():
            order = np.argsort(starts, kind="stable")
            out = np.empty(len(starts), np.uint64)
            out[order] = span_hashes(codes, starts[order], ends[order], block)
            return out
        cuts = np.unique([0, *np.searchsorted(starts, np.arange(block, len(codes), block)), len(starts)]).tolist()
        return np.concatenate([_hashes(codes[starts[a] : ends[a:b].max()], starts[a:b] - starts[a], ends[a:b] - starts[a]) for a, b in zip(cuts, cuts[1:], strict=False)])
    return _hashes(codes, starts, ends)


def _hashes(codes: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    up, down = powers(len(codes) + 1)
    total = np.empty(len(codes) + 1, np.uint64)
    total[0] = 0
    np.cumsum((codes.astype(np.uint64) + np.uint64(1)) * up[: len(codes)], out=total[1:])
    return mix64((total[ends] - total[starts]) * down[starts] + (ends - starts).astype(np.uint64))


def sliced(it: Iterator[pa.RecordBatch], rows: int = 1000) -> Iterator[pa.RecordBatch]:
    """Smaller batches, so that a task turns few texts at a time into Python objects."""
    for got in it:
        for k in range(0, max(1, got.num_rows), rows):
            yield got.slice(k, rows)


def batch(schema: pa.Schema, *columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([c if isinstance(c, (pa.Array, pa.ChunkedArray)) else pa.array(c, f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)
