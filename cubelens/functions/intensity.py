"""Colours of cells: how far a cell is from what independence would give, and the baselines."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

IMAGE = ["xdim", "ydim", "zdim", "slab"]


def heat_red(v: Column, s: Column) -> Column:
    """0 up to the expected value, 1 from twice it on; 0 where nothing positive is expected."""
    return F.when((s > 0) & (v > s), F.least(F.lit(1.0), v / F.nullif(s, F.lit(0.0)) - 1)).otherwise(0.0)


def heat_blue(v: Column, s: Column) -> Column:
    """1 for an empty cell, 0 from the expected value on."""
    return F.when((s > 0) & (v <= s), F.least(F.lit(1.0), 1 - v / F.nullif(s, F.lit(0.0)))).otherwise(0.0)


def slab_share(bins: int, z_parts: int) -> Column:
    """Share of the third axis' bins that lie in a slab: by the plan, whether rows fall into it or not."""
    if z_parts <= 1:
        return F.lit(1.0)
    held = [sum(1 for b in range(bins) if b * z_parts // bins == s) / bins for s in range(z_parts)]
    return F.element_at(F.lit(held), F.col("slab") + 1)


def with_expected(cells: DataFrame, bins: int, scope: str = "slab", z_parts: int = 1) -> DataFrame:
    """``cells`` with ``expected`` = S: a total divided by the number of cells of an image.

    ``slab``: the image's own total. ``dataset_share``: the total over all slabs of the same
    three dimensions, times the slab's share of the axis' bins (``z_parts`` slabs, some of which
    may be narrower or empty). ``dataset``: that total itself.
    """
    if scope not in ("slab", "dataset", "dataset_share"):
        raise ValueError(scope)
    keys = IMAGE if scope == "slab" else IMAGE[:3]
    total = cells.groupBy(*keys).agg(F.sum("v").alias("total_"))
    out = cells.join(total, keys)
    share = F.col("total_") / F.lit(float(bins * bins))
    if scope == "dataset_share":
        share = share * slab_share(bins, z_parts)
    return out.withColumn("expected", share).drop("total_")


def diverging(cells: DataFrame, bins: int, scope: str = "slab", z_parts: int = 1) -> DataFrame:
    """Red above and blue below the expected value; black and marked where it is not positive."""
    out = with_expected(cells, bins, scope, z_parts)
    v, s = F.col("v"), F.col("expected")
    return out.select("*", heat_red(v, s).alias("r"), F.lit(0.0).alias("g"), heat_blue(v, s).alias("b"), (s <= 0).alias("degenerate"))


def densify(cells: DataFrame, bins: int) -> DataFrame:
    """All cells of every image; absent ones have value 0. For rendering and percentiles only."""
    spark = cells.sparkSession
    grid = F.explode(F.sequence(F.lit(0), F.lit(bins * bins - 1))).alias("cell")
    full = cells.select(*IMAGE).distinct().select("*", grid).select(*IMAGE, F.expr(f"cell div {bins}").cast("int").alias("x"), F.expr(f"cell % {bins}").cast("int").alias("y"))
    return full.join(cells, [*IMAGE, "x", "y"], "left").fillna(0, ["v"])


def grayscale(cells: DataFrame, bins: int) -> DataFrame:
    """Baseline: gray between the 5th and the 95th percentile over all cells of the image."""
    full = densify(cells.select(*IMAGE, "x", "y", "v"), bins)
    ends = full.groupBy(*IMAGE).agg(F.percentile("v", [0.05, 0.95]).alias("p"))
    out = full.join(ends, IMAGE)
    low, high = F.col("p")[0], F.col("p")[1]
    gray = F.when(high > low, F.least(F.lit(1.0), F.greatest(F.lit(0.0), (F.col("v") - low) / (high - low)))).otherwise(0.0)
    return out.select(*IMAGE, "x", "y", "v", gray.alias("gray"))


def max_scaled(cells: DataFrame, bins: int) -> DataFrame:
    """Baseline: red grows up to the image's largest cell, so one peak dims all others."""
    out = with_expected(cells, bins)
    top = out.groupBy(*IMAGE).agg(F.max("v").alias("top"))
    out = out.join(top, IMAGE)
    v, s = F.col("v"), F.col("expected")
    red = F.when(v > s, (v - s) / F.nullif(F.col("top") - s, F.lit(0.0))).otherwise(0.0)
    return out.select(*IMAGE, "x", "y", "v", "expected", red.alias("r"), heat_blue(v, s).alias("b"))


def marginal_expected(cells: DataFrame) -> DataFrame:
    """Baseline for uneven bins: a cell's expected value is its row's total times its column's, over the image's."""
    rows = cells.groupBy(*IMAGE, "x").agg(F.sum("v").alias("rx"))
    cols = cells.groupBy(*IMAGE, "y").agg(F.sum("v").alias("cy"))
    total = cells.groupBy(*IMAGE).agg(F.sum("v").alias("t"))
    out = cells.join(rows, [*IMAGE, "x"]).join(cols, [*IMAGE, "y"]).join(total, IMAGE)
    s = F.when(F.col("t") != 0, F.col("rx") * F.col("cy") / F.nullif(F.col("t").cast("double"), F.lit(0.0))).otherwise(0.0)
    out = out.withColumn("expected", s)
    v, s = F.col("v"), F.col("expected")
    return out.select(*IMAGE, "x", "y", "v", "expected", heat_red(v, s).alias("r"), heat_blue(v, s).alias("b"))


def colour(cells: DataFrame, bins: int, intensity=None) -> DataFrame:
    """Any intensity: a function of (value, expected) to three columns red, green, blue."""
    if intensity is None:
        return diverging(cells, bins)
    out = with_expected(cells, bins)
    r, g, b = intensity(F.col("v"), F.col("expected"))
    return out.select("*", r.alias("r"), g.alias("g"), b.alias("b"))


def population_layout(binned: DataFrame, bin_col: str) -> DataFrame:
    """(bin, start, width): bins drawn as wide as their share of rows."""
    n = binned.groupBy(F.col(bin_col).cast("int").alias("bin")).agg(F.count("*").alias("n"))
    order = Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)  # at most as many rows as bins
    total = n.agg(F.sum("n")).scalar()
    return n.select("bin", (F.coalesce(F.sum("n").over(order), F.lit(0)) / total).alias("start"), (F.col("n") / total).alias("width"))
