"""Scratch tables in the folder that driver and executors share.

Lineage is cut by writing a Parquet table there: an executor may be lost at any
time without losing the rows, and the table is column-pruned when read again.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Sides of at most this many (narrow) rows and bytes of Parquet may be broadcast; larger ones shuffle.
BROADCAST_ROWS, BROADCAST_BYTES = 2_000_000, 64 << 20


def file_system(spark: SparkSession, path: str):
    """Hadoop's path object of ``path`` and its file system."""
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p, p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def shared_dir(spark: SparkSession) -> str:
    """The cluster's ``spark.checkpoint.dir``; in local mode (tests) a temporary folder where it is unset."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        found = tempfile.mkdtemp(prefix="tinyff-shared-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def scratch_root(spark: SparkSession) -> str:
    """The application's own scratch folder, deleted when the application ends."""
    root = f"{shared_dir(spark)}/tinyff-scratch/{spark.sparkContext.applicationId}"
    path, fs = file_system(spark, root)
    if not fs.exists(path):
        fs.mkdirs(path)
        fs.deleteOnExit(path)
    return root


def scratch_path(spark: SparkSession, tag: str) -> str:
    """A fresh path under the application's scratch folder."""
    return f"{scratch_root(spark)}/{tag}-{uuid.uuid4().hex}"


def materialise(df: DataFrame, tag: str) -> DataFrame:
    """Writes ``df`` once to the shared folder and returns the table read back."""
    spark = df.sparkSession
    path = scratch_path(spark, tag)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def small_side(df: DataFrame, most: int = BROADCAST_ROWS, most_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """``df`` (a cheap, written table) with a broadcast hint if it has at most ``most`` rows and ``most_bytes`` bytes, else as it is.

    Bytes come from the sizes of its files; the count is one number a task, read from file footers.
    """
    size = int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    return F.broadcast(df) if size <= most_bytes and df.count() <= most else df


def drop_scratch(spark: SparkSession) -> None:
    """Deletes every scratch table of this application."""
    path, fs = file_system(spark, scratch_root(spark))
    fs.delete(path, True)


def hash60(key: Column) -> Column:
    """60 bits of md5 over the key's text form, as a non-negative long; null hashes as the empty text."""
    return F.conv(F.substring(F.md5(F.coalesce(key.cast("string"), F.lit(""))), 1, 15), 16, 10).cast("long")


def spread(df: DataFrame, *cols: str) -> DataFrame:
    """Hash-partitions ``df`` on ``cols`` into the session's number of shuffle partitions."""
    return df.repartition(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), *cols)
