"""Tables written to the shared folder, to cut lineage and to survive lost executors."""

from __future__ import annotations

import re
import uuid
from collections.abc import Iterable
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

#: Used only where the session names no folder and all of it runs in one process.
FALLBACK_DIR = "/tmp/checkpoints"
#: For tables whose rows are megabytes long: pages and row groups end after any row, so that few are held at a time.
LONG_ROWS = {"parquet.page.size.row.check.min": "1", "parquet.block.size.row.check.min": "1", "parquet.block.size": str(1 << 24), "parquet.enable.dictionary": "false"}


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir`` of the session.

    Without it only a local session gets a folder; on a cluster a folder of one machine would
    lose data, so that is an error.
    """
    named = spark.conf.get("spark.checkpoint.dir", "")
    if not named and not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise RuntimeError("spark.checkpoint.dir is not set: name a folder that driver and executors share")
    return (named or FALLBACK_DIR).rstrip("/")


def materialize(df: DataFrame, name: str = "t", options: dict[str, str] = {}) -> DataFrame:  # noqa: B006
    """Write ``df`` as Parquet in the shared folder and return a reader of it.

    The files outlive the executors, later reads prune columns, and the plan above
    starts from a scan. ``release`` removes them.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/cubelens/{name}-{uuid.uuid4().hex}"
    df.write.options(**options).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._shared_paths = [path]
    return out


@contextmanager
def passing_shuffles(spark: SparkSession):
    """Exchange files of jobs that run inside are deleted as soon as a job has ended, not when its plan is collected."""
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    old = spark.conf.get(key, "false")
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        spark.conf.set(key, old)


@contextmanager
def small_scans(spark: SparkSession):
    """Scans of jobs that run inside are cut into tasks of at most 32 MiB: packed rows take long a byte, and few large tasks leave cores idle at the end."""
    key = "spark.sql.files.maxPartitionBytes"
    old = spark.conf.get(key)
    spark.conf.set(key, str(min(1 << 25, spark._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(old))))
    try:
        yield
    finally:
        spark.conf.set(key, old)


def materialize_each(frames: Iterable[DataFrame], name: str = "t", options: dict[str, str] = {}) -> DataFrame:  # noqa: B006
    """The union of frames that are made and written one after another: exchanges of one are gone before the next begins."""
    path, out = None, None
    for df in frames:
        spark = df.sparkSession
        path = path or f"{shared_dir(spark)}/cubelens/{name}-{uuid.uuid4().hex}"
        with passing_shuffles(spark):
            df.write.mode("append").options(**options).parquet(path)
        if out is None:
            out = spark.read.schema(df.schema), path
    table = out[0].parquet(path)
    table._shared_paths = [path]
    return table


def keep(df: DataFrame, *tables: DataFrame | None) -> DataFrame:
    """``df``, remembering that it is read from these written tables, so that ``release(df)`` deletes them."""
    df._shared_paths = [p for t in tables for p in getattr(t, "_shared_paths", [])]
    return df


def release(df: DataFrame | None) -> None:
    """Delete the files behind a frame that ``materialize`` or ``keep`` returned; others have none."""
    for path in getattr(df, "_shared_paths", []):
        spark = df.sparkSession
        place = spark._jvm.org.apache.hadoop.fs.Path(path)
        place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)
