"""Other ways to bin an axis, for comparison with equal populations."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cubelens.dimension import DimensionSpec
from cubelens.operators.binning import _div, bin_type, width
from cubelens.operators.rank import running
from cubelens.storage import keep


def bin_equidepth_whole(df: DataFrame, spec: DimensionSpec, bins: int) -> DataFrame:
    """``b_<dim>`` and ``width``: equal depth without splitting a value; bins differ in population and are drawn that wide.

    Distinct values are counted first; their running total, taken by ranges of the order,
    decides, and joins back by value.
    """
    v = spec.label()
    values = running(df.groupBy(v.alias("value_")).agg(F.count("*").alias("n")), [F.col("value_").asc_nulls_first()], "n")
    n = values.agg(F.sum("n")).first()[0] or 0
    placed = values.select("value_", "n", _div(F.col("before_"), width(n, bins)).alias("raw_"))
    ids = placed.groupBy("raw_").agg(F.sum("n").alias("rows_"))
    ids = ids.withColumn(spec.bin, (F.row_number().over(Window.orderBy("raw_")) - 1).cast(bin_type(bins)))  # as many rows as bins at most
    placed = placed.join(ids, "raw_").select("value_", spec.bin, (F.col("rows_") / F.lit(n)).alias("width"))
    return keep(df.withColumn("v_", v).join(placed, F.col("v_").eqNullSafe(F.col("value_"))).drop("v_", "value_"), values)


def bin_equidistance(df: DataFrame, expression: str, bins: int, low: float | None = None, high: float | None = None, name: str = "b") -> DataFrame:
    """Equal-width bins of the value range; the top edge falls into the last bin, nulls into none, a single value into bin 0."""
    v = F.expr(expression).cast("double")
    if low is None or high is None:
        a, z = df.agg(F.min(v), F.max(v)).first()
        low, high = (a if low is None else low), (z if high is None else high)
    if low is None or low == high:
        return df.withColumn(name, F.when(v.isNotNull(), 0).cast("int"))
    return df.withColumn(name, F.when((v >= low) & (v <= high), F.least(F.width_bucket(v, F.lit(float(low)), F.lit(float(high)), F.lit(bins)) - 1, F.lit(bins - 1))).cast("int"))


def clip_rows(df: DataFrame, bounds: dict[str, tuple[float, float]]) -> DataFrame:
    """Hand-picked cleaning: keep rows whose columns lie in the bounds; reaches the scan as a filter."""
    for c, (low, high) in bounds.items():
        df = df.filter(F.col(c).between(low, high))
    return df


def bin_categorical(df: DataFrame, expression: str, name: str = "b") -> DataFrame:
    """One bin for each distinct value in order; the distinct values are numbered, by ranges of the order, not the rows."""
    v = F.expr(expression)
    values = running(df.select(v.alias("value_")).distinct(), [F.col("value_").asc_nulls_first()])
    table = values.select("value_", F.col("place_").cast("int").alias(name))
    return keep(df.withColumn("v_", v).join(table, F.col("v_").eqNullSafe(F.col("value_"))).drop("v_", "value_"), values)


def bin_packed(df: DataFrame, expression: str, bins: int, name: str = "b") -> DataFrame:
    """A composite packed into one number, then equal widths: the gaps between packed ranges skew it."""
    return bin_equidistance(df, expression, bins, name=name)
