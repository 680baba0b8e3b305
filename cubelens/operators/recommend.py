"""Which images to look at first."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cubelens.dimension import DimensionSpec
from cubelens.functions.intensity import IMAGE, heat_blue, heat_red, with_expected
from cubelens.plans.triples import triples_of

HEURISTICS = {
    "red": lambda v, s: heat_red(v, s),
    "blue": lambda v, s: heat_blue(v, s),
    "brightness": lambda v, s: heat_red(v, s) + heat_blue(v, s),
    "chi_square": lambda v, s: (v - s) * (v - s) / F.nullif(s, F.lit(0.0)),
    "information": lambda v, s: F.when((v > 0) & (s > 0), v / F.nullif(s, F.lit(0.0)) * F.ln(v / F.nullif(s, F.lit(0.0)))).otherwise(0.0),
}


#: What an absent cell adds to a heuristic; nothing where not listed.
_ABSENT = {"blue": lambda s: F.lit(1.0), "brightness": lambda s: F.lit(1.0), "chi_square": lambda s: s}


def score_images(cells: DataFrame, bins: int, scope: str = "slab", heuristic: str = "red", z_parts: int = 1) -> DataFrame:
    """(xdim, ydim, zdim, slab, total, expected, score, degenerate): the mean of a heuristic over all cells.

    Needs no picture: cells become numbers and are added up. Absent cells have no red; for
    heuristics that empty cells add to, their number counts.
    """
    size = float(bins * bins)
    s = with_expected(cells, bins, scope, z_parts)
    h = HEURISTICS[heuristic]
    out = s.groupBy(*IMAGE).agg(F.sum("v").alias("total"), F.first("expected").alias("expected"), F.sum(h(F.col("v"), F.col("expected"))).alias("sum_"), F.count("*").alias("n_"))
    empty = _ABSENT.get(heuristic, lambda s: F.lit(0.0))(F.col("expected"))
    return out.select(*IMAGE, "total", "expected", ((F.col("sum_") + empty * (F.lit(size) - F.col("n_"))) / size).alias("score"), (F.col("expected") <= 0).alias("degenerate"))


def score_cube(cube: DataFrame, specs: list[DimensionSpec], bins: int, z_parts: int = 4, value: str = "cnt", heuristic: str = "red") -> DataFrame:
    """``score_images`` of all slab images, straight from the cube's cells.

    Images and their cells are numbered, so that exchanges carry three numbers a cell; an
    image's values (at most bins x bins) meet in one array, from which its total and its score
    are taken at once. Names come last, on one row an image.
    """
    size, triples, names = float(bins * bins), triples_of(len(specs)), [s.name for s in specs]
    roles = []
    for z in range(3):
        x, y = (k for k in range(3) if k != z)
        image = (F.col("triple") * 3 + z) * z_parts + F.expr(f"(b{z} * {z_parts}) div {bins}").cast("int")
        roles.append(F.struct(image.alias("image"), (F.col(f"b{x}") * bins + F.col(f"b{y}")).alias("cell")))
    melted = cube.select(F.explode(F.array(*roles)).alias("i"), F.col(value).alias("v"))
    cells = melted.groupBy("i.image", "i.cell").agg(F.sum("v").alias("v"))
    images = cells.groupBy("image").agg(F.sum("v").alias("total"), F.collect_list("v").alias("vs")).withColumn("expected", F.col("total") / F.lit(size))
    h, s = HEURISTICS[heuristic], F.col("expected")
    empty = _ABSENT.get(heuristic, lambda s: F.lit(0.0))(s)
    score = (F.aggregate("vs", F.lit(0.0), lambda a, v: a + h(v, s).cast("double")) + empty * (F.lit(size) - F.size("vs"))) / size
    triple, role = F.expr(f"image div {3 * z_parts}").cast("int"), F.expr(f"(image div {z_parts}) % 3").cast("int")

    def named(place: int) -> Column:
        """Name of the drawn (0, 1) or the partitioning (2) dimension, by triple and role."""
        table = [names[t[[k for k in range(3) if k != z][place] if place < 2 else z]] for t in triples for z in range(3)]
        return F.element_at(F.lit(table), triple * 3 + role + 1)

    return images.select(named(0).alias("xdim"), named(1).alias("ydim"), named(2).alias("zdim"), F.expr(f"image % {z_parts}").cast("int").alias("slab"), "total", "expected", score.alias("score"), (s <= 0).alias("degenerate"))


def score_groups(images: DataFrame, ascending: bool = False) -> DataFrame:
    """(xdim, ydim, score, images, group_rank): sums over all images of an axis pair.

    There are as many groups as pairs of dimensions, so one task ranks them.
    """
    groups = images.groupBy("xdim", "ydim").agg(F.sum("score").alias("score"), F.count("*").alias("images"))
    key = F.round("score", 9)
    order = Window.orderBy(key.asc() if ascending else key.desc(), "xdim", "ydim")
    return groups.withColumn("group_rank", F.row_number().over(order))


def recommend(images: DataFrame, m: int, n: int, ascending: bool = False) -> DataFrame:
    """Top n images of the top m groups (or of the lowest groups)."""
    groups = score_groups(images, ascending).filter(F.col("group_rank") <= m).select("xdim", "ydim", "group_rank")
    inside = Window.partitionBy("xdim", "ydim").orderBy(F.round("score", 9).desc(), "zdim", "slab")
    return images.join(groups, ["xdim", "ydim"]).withColumn("image_rank", F.row_number().over(inside)).filter(F.col("image_rank") <= n).select("group_rank", "image_rank", *IMAGE, "score")


def prioritise(images: DataFrame) -> DataFrame:
    """(…, appearance, priority): an axis pair's second image ranks behind every pair's first, and so on.

    A row for each image: twelve for each triple.
    """
    pair = Window.partitionBy("xdim", "ydim").orderBy(F.round("score", 9).desc(), "zdim", "slab")
    seen = images.withColumn("appearance", F.row_number().over(pair))
    return seen.withColumn("priority", F.row_number().over(Window.orderBy("appearance", F.round("score", 9).desc(), *IMAGE)))


def noise_floor(expected: Column) -> Column:
    """Mean red of an image without structure whose cells hold Poisson counts of this mean.

    The square-root law of large means; a term that fades from mean 1 on bends it for small ones.
    """
    return F.lit(0.3989) / F.sqrt(expected + F.lit(1.283) * F.exp(F.lit(-0.518) * (expected - 1)))


def score_minus_noise(images: DataFrame, entities_per_row: float = 1.0) -> DataFrame:
    """Scores less the floor at the images' density of independent entities."""
    return images.withColumn("excess", F.col("score") - noise_floor(F.col("expected") * entities_per_row))
