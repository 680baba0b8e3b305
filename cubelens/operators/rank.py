"""Ranks: the place of every row in the order of every dimension, computed once and kept."""

from __future__ import annotations

from itertools import accumulate

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cubelens.dimension import DimensionSpec, resolve, tie_order
from cubelens.storage import keep, materialize, release

_LOCAL = (1 << 33) - 1


def _partitions(df: DataFrame, partitions: int | None) -> int:
    return partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def _lookup(table: list, place: Column) -> Column:
    return F.element_at(F.lit(table), (place + 1).cast("int"))


def build_ranks(df: DataFrame, specs: list[DimensionSpec], row_key: tuple[str, ...], tie: str = "keyed", partitions: int | None = None) -> DataFrame:
    """``df`` with one BIGINT column ``rk_<dimension>`` for every spec: 0-based place in its order.

    Rows are written with a number of their own. For every dimension only that number, the
    sort keys and the tie order go through a range exchange, all dimensions in one job; a frequent
    value is spread over many tasks, because ties are part of the order. Inside a task the
    sorted place is the low part of Spark's increasing id and the task its high part; what is
    written of that (a number and a place a row and dimension) is counted by task (one number a
    task and dimension reaches the driver) and the counts become offsets. Places then meet by
    row and join the rows once: whatever the number of dimensions, rows move at full width only
    here. No task sees all rows. ``release`` of the result deletes the ranked table.

    row_key must identify rows; its columns must be in ``df``.
    """
    resolve(df, specs)
    n = _partitions(df, partitions)
    base = materialize(df.withColumn("row_", F.monotonically_increasing_id()), "rows")
    parts = []
    for i, s in enumerate(specs):
        order = [*s.order(), *tie_order(s, row_key, tie)]
        by = [F.col(f"k{j}_") for j in range(len(order))]
        by = [c.desc_nulls_first() if j < len(s.keys) and s.keys[j].endswith(" desc") else c.asc_nulls_first() for j, c in enumerate(by)]
        keys = [F.expr(k.removesuffix(" desc")) for k in s.keys] + order[len(s.keys) :]
        narrow = base.select("row_", *[k.alias(f"k{j}_") for j, k in enumerate(keys)])
        placed = narrow.repartitionByRange(n, *by).sortWithinPartitions(*by)
        parts.append(placed.select("row_", F.lit(i).cast("smallint").alias("d"), F.monotonically_increasing_id().alias("raw")))
    placed = materialize(_all(parts), "places")
    task = F.shiftright("raw", 33)
    sizes = placed.groupBy("d", task.alias("p")).agg(F.count("*").alias("n")).collect()  # tasks times dimensions
    count = {(r.d, r.p): r.n for r in sizes}
    most = max((p for _, p in count), default=-1) + 1
    starts = [[0, *accumulate(count.get((i, p), 0) for p in range(most))] for i in range(len(specs))]
    rank = lambda i: F.max(F.when(F.col("d") == i, _lookup(starts[i], F.shiftright("raw", 33)) + F.col("raw").bitwiseAND(_LOCAL)))
    ranks = placed.repartition(n, "row_").groupBy("row_").agg(*[rank(i).alias(s.rank) for i, s in enumerate(specs)])
    old = {s.rank for s in specs}
    out = materialize(base.join(ranks, "row_").select(*[c for c in df.columns if c not in old], *[s.rank for s in specs]), "ranked")
    release(placed)
    release(base)
    return out


def _all(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def running(df: DataFrame, order: list[Column], value: str | None = None, partitions: int | None = None) -> DataFrame:
    """``df`` with ``place_``, the 0-based place of a row in the order, and ``before_``, the sum of ``value`` over the rows before.

    One range exchange, then sums inside its tasks; a number or two of each task reach the driver.
    """
    placed = materialize(df.repartitionByRange(_partitions(df, partitions), *order).sortWithinPartitions(*order).withColumn("raw_", F.monotonically_increasing_id()), "running")
    amount = F.sum(value) if value else F.lit(0).cast("long")
    sizes = {r.p: (r.n, r.v) for r in placed.groupBy(F.shiftright("raw_", 33).alias("p")).agg(F.count("*").alias("n"), amount.alias("v")).collect()}
    most = max(sizes, default=-1) + 1
    starts, sums = ([0, *accumulate(sizes.get(p, (0, 0))[k] or 0 for p in range(most))] for k in (0, 1))
    task = F.shiftright("raw_", 33)
    out = placed.withColumn("place_", _lookup(starts, task) + F.col("raw_").bitwiseAND(_LOCAL))
    if value:
        inside = Window.partitionBy(task).orderBy("raw_").rowsBetween(Window.unboundedPreceding, -1)
        out = out.withColumn("before_", _lookup(sums, task) + F.coalesce(F.sum(value).over(inside), F.lit(0)))
    return keep(out.drop("raw_"), placed)


def rank_small(df: DataFrame, spec: DimensionSpec, row_key: tuple[str, ...], tie: str = "keyed") -> DataFrame:
    """The same column by one window over all rows: for inputs that one task can sort (baseline)."""
    order = Window.orderBy(*spec.order(), *tie_order(spec, row_key, tie), *row_key)
    return df.withColumn(spec.rank, (F.row_number().over(order) - 1).cast("long"))


def build_fine_buckets(df: DataFrame, specs: list[DimensionSpec], row_key: tuple[str, ...], fine_bits: int = 12, accuracy: int = 100_000) -> DataFrame:
    """``df`` with ``rk_<dimension>`` in 0 .. 2**fine_bits - 1 from quantile sketches, without any sort.

    One scan builds the sketches (numeric or time-valued first keys only), one pass assigns:
    a value equal to several cuts is spread over its run of buckets by a hash keyed with the
    dimension. Secondary keys are not used. For tables where one sort a dimension is too much.
    """
    buckets = 1 << fine_bits
    shares = [i / buckets for i in range(1, buckets)]
    number = lambda s: s.label().cast("double") if not s.keys[0].endswith(" desc") else -s.label().cast("double")
    cuts = df.agg(*[F.percentile_approx(number(s), shares, accuracy).alias(s.name) for s in specs]).first()
    for s in specs:
        known = F.lit([float(x) for x in cuts[s.name] or []])
        v = number(s)
        below = F.when(v.isNull(), 0).otherwise(_search(known, v, False))
        upto = F.when(v.isNull(), 0).otherwise(_search(known, v, True))
        spread = F.pmod(F.xxhash64(F.lit(s.name), *[F.expr(k) for k in row_key]), upto - below + 1)
        df = df.withColumn(s.rank, (below + spread).cast("long"))
    return df


def _search(cuts, v, upto: bool):
    """How many sorted cuts lie below v (or up to v), by halving an interval inside the expression."""

    def step(s, _):
        mid = ((s["lo"] + s["hi"]) / 2).cast("int")
        cut = F.element_at(cuts, mid + 1)
        right = (s["lo"] < s["hi"]) & ((cut <= v) if upto else (cut < v))
        return F.struct(F.when(right, mid + 1).otherwise(s["lo"]).alias("lo"), F.when(right | (s["lo"] >= s["hi"]), s["hi"]).otherwise(mid).alias("hi"))

    return F.aggregate(F.sequence(F.lit(1), F.lit(24)), F.struct(F.lit(0).alias("lo"), F.size(cuts).alias("hi")), step)["lo"]


def write_augmented(df: DataFrame, path: str, sort_by: str | None = None) -> None:
    """Keep the ranked table; sorted by one rank, row groups can be skipped when it is drilled into."""
    (df.sortWithinPartitions(sort_by) if sort_by else df).write.mode("overwrite").parquet(path)


def read_augmented(spark, path: str) -> DataFrame:
    return spark.read.parquet(path)
