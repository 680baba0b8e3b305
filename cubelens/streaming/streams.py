"""Structured Streaming forms: windows, late rows, deduplication, state, and the method's incremental steps."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cubelens.dimension import DimensionSpec
from cubelens.operators import binning, cube
from cubelens.storage import release, shared_dir


def scratch(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/cubelens/{name}-{uuid.uuid4().hex}"


def split_files(df: DataFrame, files: int, key: str = "event_id") -> str:
    """Rows as ``files`` Parquet files in a folder that a stream can read one after another."""
    path = scratch(df.sparkSession, "stream")
    df.withColumn("part_", F.pmod(F.col(key), F.lit(files))).repartition(files, "part_").drop("part_").write.parquet(path)
    return path


def source(spark: SparkSession, path: str, schema, files_per_batch: int = 2) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def in_order(parts: list[DataFrame], files: int = 2) -> str:
    """A folder with ``files`` files of each part, parts written one after another: a stream that takes as many files at a time reads them in turn."""
    path = scratch(parts[0].sparkSession, "ordered")
    for part in parts:
        part.repartition(files).write.mode("append").parquet(path)
    return path


def run_append(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a streaming frame over all available input; returns what it wrote.

    Every mode writes files in the shared folder. Append: all rows. Complete: the last
    batch's, which hold all of the result. Update: the rows of every batch, with the column
    ``batch``. A batch that runs again replaces its own files.
    """
    spark = stream.sparkSession
    path = scratch(spark, "out")
    w = stream.writeStream.option("checkpointLocation", scratch(spark, "cp")).outputMode(mode).trigger(availableNow=True)
    if mode == "append":
        w.format("parquet").start(path).awaitTermination()
        return spark.read.schema(stream.schema).parquet(path)
    last = [-1]

    def write(df: DataFrame, k: int) -> None:
        df.write.mode("overwrite").parquet(f"{path}/batch={k}")
        last[0] = k

    w.foreachBatch(write).start().awaitTermination()
    if last[0] < 0:
        return spark.createDataFrame([], stream.schema)
    if mode == "complete":
        return spark.read.schema(stream.schema).parquet(f"{path}/batch={last[0]}")
    return spark.read.parquet(path)


def run_batches(stream: DataFrame, fn: Callable[[DataFrame, int], None]) -> None:
    """Hand every micro-batch to a function, once for each batch number."""
    stream.writeStream.option("checkpointLocation", scratch(stream.sparkSession, "cp")).foreachBatch(fn).trigger(availableNow=True).start().awaitTermination()


class Merged:
    """A table of sums that micro-batches are merged into; a batch that is handed in again counts once.

    The current version is a written table; the next one replaces it. The table holds one row
    a key (histogram bucket or cube cell), not a row an event.
    """

    def __init__(self, spark: SparkSession, keys: list[str], sums: list[str]):
        self.spark, self.keys, self.sums, self.path, self.done = spark, keys, sums, None, set()

    def add(self, part: DataFrame, batch: int) -> None:
        if batch in self.done:
            return
        part = part.select(*self.keys, *self.sums)
        if self.path:
            part = part.unionByName(self.spark.read.parquet(self.path))
        path = scratch(self.spark, "merged")
        part.groupBy(*self.keys).agg(*[F.sum(s).alias(s) for s in self.sums]).write.parquet(path)
        old, self.path = self.path, path
        self.done.add(batch)
        if old:
            gone = self.spark.range(0)
            gone._shared_paths = [old]
            release(gone)

    def table(self) -> DataFrame:
        return self.spark.read.parquet(self.path)


def stream_histogram(stream: DataFrame, specs: list[DimensionSpec], total: int, fine_bits: int) -> DataFrame:
    """Fine histogram of ranked rows, merged batch by batch."""
    merged = Merged(stream.sparkSession, ["dim", "bucket"], ["cnt"])
    run_batches(stream, lambda df, k: merged.add(binning.fine_histogram(df, specs, total, fine_bits), k))
    return merged.table()


def stream_cube(stream: DataFrame, specs: list[DimensionSpec], bins: int) -> DataFrame:
    """Cube of binned rows, merged batch by batch."""
    merged = Merged(stream.sparkSession, ["triple", "b0", "b1", "b2"], ["cnt"])
    run_batches(stream, lambda df, k: merged.add(cube.local_dense(cube.narrow(df, specs), specs, (), bins), k))
    return merged.table()
