"""Small batches of new rows: binned by remembered bucket boundaries, without ranking again."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cubelens.dimension import DimensionSpec
from cubelens.operators.binning import bin_type, histogram_cuts, shift_of, step_function
from cubelens.storage import keep, materialize


def capture_bounds(aug: DataFrame, spec: DimensionSpec, total: int, fine_bits: int = 20) -> DataFrame:
    """(bucket, cnt, first_key): the first key value that entered each bucket of the histogram."""
    bucket = F.shiftright(spec.rank, shift_of(total, fine_bits)).cast("int")
    key = F.struct(*[F.expr(k.removesuffix(" desc")).alias(f"k{i}") for i, k in enumerate(spec.keys)])
    return aug.groupBy(bucket.alias("bucket")).agg(F.count("*").alias("cnt"), F.min_by(key, F.col(spec.rank)).alias("first_key"))


def _last_known(merged: DataFrame) -> DataFrame:
    """(k, side, run): in the order of k and side, a missing run is the last one before; bucket 0 where there is none.

    Ranges of the order are filled each by itself; the last run of a range, one a task, goes on into the next.
    """
    n = int(merged.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    placed = materialize(merged.repartitionByRange(n, "k", "side").withColumn("task_", F.spark_partition_id()), "merged")
    lasts = {r.task_: (r.run.lo, r.run.hi) for r in placed.filter("run is not null").groupBy("task_").agg(F.max_by("run", F.struct("k", "side")).alias("run")).collect()}
    carried, now = [], (0, 0)
    for task in range(n):
        carried.append(now)
        now = lasts.get(task, now)
    entry = F.struct(*[F.element_at(F.lit([c[k] for c in carried]), F.col("task_") + 1).alias(name) for k, name in enumerate(("lo", "hi"))])
    before = Window.partitionBy("task_").orderBy("k", "side").rowsBetween(Window.unboundedPreceding, 0)
    return keep(placed.withColumn("run", F.coalesce(F.last("run", ignorenulls=True).over(before), entry)).drop("task_"), placed)


def bucket_runs(new_rows: DataFrame, bounds: DataFrame, spec: DimensionSpec) -> DataFrame:
    """(k, run): for every distinct key of the new rows, the buckets (lo to hi) that begin with the last first key not above it.

    Several buckets where a value spans them; bucket 0 below all first keys.
    """
    keys = new_rows.select(_key(spec).alias("key_")).distinct()
    # one run of buckets for each boundary key
    runs = bounds.groupBy("first_key").agg(F.min("bucket").alias("lo"), F.max("bucket").alias("hi"))
    merged = runs.select(F.col("first_key").alias("k"), F.lit(0).alias("side"), F.struct("lo", "hi").alias("run")).unionByName(
        keys.select(F.col("key_").alias("k"), F.lit(1).alias("side"), F.lit(None).cast("struct<lo:int,hi:int>").alias("run"))
    )
    found = _last_known(merged)
    return keep(found.filter("side = 1").select("k", "run"), found)


def _key(spec: DimensionSpec):
    return F.struct(*[F.expr(k).alias(f"k{i}") for i, k in enumerate(spec.keys)])


def bin_inserts(new_rows: DataFrame, bounds: DataFrame, spec: DimensionSpec, bins: int, row_key: tuple[str, ...]) -> tuple[DataFrame, DataFrame]:
    """New rows with ``b_<dim>``, and the cuts (dim, bin, first_bucket, first_pos) of the histogram with them counted in.

    A row goes to the last bucket whose first key is not above its own, as-of; a key that
    several buckets begin with is spread over them by a hash of the row; one below all goes to
    bucket 0. Ascending keys. Distinct keys of the new rows, not the rows, meet the bounds.
    """
    rows = new_rows.withColumn("key_", _key(spec))
    found = bucket_runs(new_rows, bounds, spec)
    runs = found.select(F.col("k").alias("bound_"), F.col("run").alias("run_"))
    spread = F.pmod(F.xxhash64(F.lit(spec.name), *[F.expr(k) for k in row_key]), F.col("run_.hi") - F.col("run_.lo") + 1)
    placed = rows.join(runs, F.col("key_").eqNullSafe(F.col("bound_"))).withColumn("bucket_", (F.col("run_.lo") + spread).cast("int")).drop("bound_", "run_", "key_")
    added = placed.groupBy(F.col("bucket_").alias("bucket")).agg(F.count("*").alias("cnt"))
    hist = bounds.select("bucket", "cnt").unionByName(added).groupBy("bucket").agg(F.sum("cnt").alias("cnt")).select(F.lit(spec.name).alias("dim"), "bucket", "cnt")
    n = hist.agg(F.sum("cnt")).first()[0] or 0
    cuts = histogram_cuts(hist, n, bins)
    steps = sorted((r.first_bucket, r.bin) for r in cuts.collect())  # at most ``bins`` cuts
    at = step_function(F.col("bucket_"), [b for b, _ in steps]) if steps else F.lit(0)
    out = placed.withColumn(spec.bin, F.element_at(F.lit([k for _, k in steps] or [0]), at + 1).cast(bin_type(bins))).drop("bucket_")
    return keep(out, found), cuts
