"""Intermediate tables in the folder that the whole cluster shares.

A table written here cuts lineage and survives a lost executor: every reader
gets the same committed files, whatever is computed again upstream.
"""

from __future__ import annotations

import atexit
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

CHECKPOINT_DIR = "spark.checkpoint.dir"


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder; a temporary one of our own only in a single local JVM that names none (tests)."""
    named = spark.conf.get(CHECKPOINT_DIR, None)
    if named:
        return named
    master = spark.conf.get("spark.master", "")
    if not re.match(r"local(\[|$)", master):
        raise ValueError(f"{CHECKPOINT_DIR} must name a folder that all of {master} shares")
    own = getattr(spark, "_quadpost_shared", None)
    if own is None:
        own = f"file://{tempfile.mkdtemp(prefix='quadpost-')}"
        spark._quadpost_shared = own
    return own


def _delete(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        target = jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
    except Exception:  # the session has ended: the folder's owner clears it
        pass


def written(df: DataFrame, name: str, partition_by: list[str] | None = None) -> DataFrame:
    """``df`` as a Parquet table in the shared folder, read again. Removed when the driver ends."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    writer = df.write.option("compression", "zstd")
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.parquet(path)
    atexit.register(_delete, spark, path)
    held = spark.read.schema(df.schema).parquet(path)
    held._quadpost_path = path
    return held


def drop(held: DataFrame) -> None:
    """Deletes a table of ``written`` that nothing reads any more."""
    _delete(held.sparkSession, held._quadpost_path)


def shuffle_parts(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))
