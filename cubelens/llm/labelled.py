"""Bounded, deterministic samples of labelled rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cubelens.llm.quality_rules import with_ids

FOLDS = 5


def held_out(doc_id: Column) -> Column:
    """True for the fifth of the ids that no model learns from; false for null."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % FOLDS == 0, F.lit(False))


def training_rows(docs: DataFrame, labels: DataFrame, label: str, per_class: int) -> DataFrame:
    """Rows of ``docs`` with their label: at most ``per_class`` ids of each class, by hash order, none held out.

    Of an id labelled twice the larger label counts; rows without a label are left out. An id
    that repeats in ``docs`` gives one row.
    """
    ids = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("y")).filter("doc_id is not null and y in (0, 1)")
    ids = ids.groupBy("doc_id").agg(F.max("y").alias("y")).filter(~held_out(F.col("doc_id")))
    picked = None
    for y in (0, 1):
        one = ids.filter(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(per_class)
        picked = one if picked is None else picked.unionByName(one)
    picked = picked.sparkSession.createDataFrame([(r.doc_id, r.y) for r in picked.collect()], "doc_id long, y int")  # at most 2 * per_class rows
    return with_ids(docs, picked).join(F.broadcast(picked), "doc_id").dropDuplicates(["doc_id"])
