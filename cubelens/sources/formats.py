"""File formats: readers and writers of the same rows."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubelens.storage import shared_dir


def write(df: DataFrame, fmt: str, path: str, partition_by: list[str] | None = None, bucket_by: tuple[int, str] | None = None, table: str | None = None) -> None:
    """Files of a format, partitioned by columns; or a bucketed table for joins without an exchange."""
    w = df.write.mode("overwrite").format(fmt)
    w = w.partitionBy(*partition_by) if partition_by else w
    if bucket_by:
        w.bucketBy(*bucket_by).sortBy(bucket_by[1]).saveAsTable(table)
    else:
        w.option("header", True).save(path) if fmt == "csv" else w.save(path)


def read(spark, fmt: str, path: str, schema=None) -> DataFrame:
    r = spark.read.format(fmt)
    r = r.schema(schema) if schema is not None else r
    return (r.option("header", True) if fmt == "csv" else r).load(path)


def roundtrip(df: DataFrame) -> DataFrame:
    """The rows of ``df`` once for each format, written and read again."""
    spark, out = df.sparkSession, None
    for fmt in ("csv", "json", "orc", "parquet", "text"):
        path = f"{shared_dir(spark)}/cubelens/{fmt}-{uuid.uuid4().hex}"
        if fmt == "text":
            write(df.select(F.to_json(F.struct(*df.columns)).alias("value")), fmt, path)
            back = spark.read.text(path).select(F.from_json("value", df.schema).alias("r")).select("r.*")
        else:
            write(df, fmt, path)
            back = read(spark, fmt, path, df.schema)
        part = back.select(F.lit(fmt).alias("fmt"), *df.columns)
        out = part if out is None else out.unionByName(part)
    return out
