"""Images from cubes: each member of a triple in turn as the partitioning axis, cut into slabs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubelens.dimension import DimensionSpec
from cubelens.plans.triples import triples_of


def slab_images(cube: DataFrame, specs: list[DimensionSpec], bins: int, z_parts: int = 4, value: str = "cnt", z_roles: str = "all", z_between: tuple[int, int] | None = None) -> DataFrame:
    """(xdim, ydim, zdim, slab, x, y, v): cells summed over ranges of the third axis.

    A cell takes part once for each role; sums are partial before the exchange. x is the
    lower-numbered of the two drawn dimensions. ``z_between`` keeps one range of z bins as slab 0.
    """
    names = [s.name for s in specs]
    triples = triples_of(len(specs))
    roles = []
    for z in range(3) if z_roles == "all" else (int(z_roles),):
        x, y = (k for k in range(3) if k != z)
        pick = lambda k: F.element_at(F.lit([names[t[k]] for t in triples]), F.col("triple") + 1)
        slab = F.expr(f"(b{z} * {z_parts}) div {bins}").cast("int") if z_between is None else F.when(F.col(f"b{z}").between(*z_between), 0)
        roles.append(F.struct(pick(x).alias("xdim"), pick(y).alias("ydim"), pick(z).alias("zdim"), slab.alias("slab"), F.col(f"b{x}").alias("x"), F.col(f"b{y}").alias("y")))
    cells = cube.select(F.explode(F.array(*roles)).alias("i"), F.col(value).alias("v")).filter("i.slab is not null")
    return cells.groupBy("i.xdim", "i.ydim", "i.zdim", "i.slab", "i.x", "i.y").agg(F.sum("v").alias("v"))


def pair_images(pairs: DataFrame, specs: list[DimensionSpec], value: str = "cnt") -> DataFrame:
    """The same contract for plain two-dimensional aggregates."""
    from itertools import combinations

    both = list(combinations([s.name for s in specs], 2))
    name = lambda k: F.element_at(F.lit([p[k] for p in both]), F.col("pair") + 1)
    return pairs.select(name(0).alias("xdim"), name(1).alias("ydim"), F.lit("").alias("zdim"), F.lit(0).alias("slab"), F.col("b0").alias("x"), F.col("b1").alias("y"), F.col(value).alias("v"))


def hover(axis: DataFrame, xdim: str, ydim: str, x: int, y: int) -> DataFrame:
    """Value ranges behind a cell."""
    return axis.filter(((F.col("dim") == xdim) & (F.col("bin") == x)) | ((F.col("dim") == ydim) & (F.col("bin") == y)))


def drill(binned: DataFrame, cells: dict[str, tuple[int, int]]) -> DataFrame:
    """Source rows behind ranges of bins; bins are columns of the table, so Parquet can skip."""
    for column, (low, high) in cells.items():
        binned = binned.filter(F.col(column).between(low, high))
    return binned
