"""The whole path from a table to ranked images, and a session that reuses its ranks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cubelens.dimension import DimensionSpec, MeasureSpec
from cubelens.functions.intensity import IMAGE, diverging
from cubelens.operators import binning, cube, image, insert, recommend, render
from cubelens.operators.rank import build_ranks
from cubelens.storage import materialize


class Session:
    """One table, ranked once; many subsets, resolutions, measures and picture sets after that.

    Only the ranked table is written; sessions of several analysts may read the same one.
    """

    def __init__(self, augmented: DataFrame, specs: list[DimensionSpec], row_key: tuple[str, ...], total: int):
        self.augmented, self.specs, self.row_key, self.total = augmented, specs, row_key, total

    @classmethod
    def prepare(cls, df: DataFrame, specs: list[DimensionSpec], row_key: tuple[str, ...], tie: str = "keyed") -> Session:
        ranked = build_ranks(df, specs, row_key, tie)
        return cls(ranked, specs, row_key, ranked.count())

    def reuse(self, specs: list[DimensionSpec]) -> Session:
        """The same ranks for fewer dimensions."""
        return Session(self.augmented, specs, self.row_key, self.total)

    def bin(self, where: str | Column | None = None, bins: int = binning.BINS, fine_bits: int = binning.FINE_BITS) -> DataFrame:
        rows = self.augmented if where is None else self.augmented.filter(where)
        return binning.bin_auto(rows, self.specs, self.total, bins, fine_bits)

    def cube(self, binned: DataFrame, bins: int, measures: list[MeasureSpec] = (), strategy: str = "auto", **options) -> DataFrame:
        return cube.build_cube(binned, self.specs, bins, measures, strategy, **options)

    def images(self, cells: DataFrame, bins: int, z_parts: int = 4, value: str = "cnt") -> DataFrame:
        return image.slab_images(cells, self.specs, bins, z_parts, value)

    def insert(self, new_rows: DataFrame, spec: DimensionSpec, bins: int, fine_bits: int = binning.FINE_BITS) -> DataFrame:
        bounds = insert.capture_bounds(self.augmented, spec, self.total, fine_bits)
        return insert.bin_inserts(new_rows, bounds, spec, bins, self.row_key)[0]


def explore(df: DataFrame, specs: list[DimensionSpec], row_key: tuple[str, ...], where=None, bins: int = 16, measures=(), z_parts: int = 4, m: int = 30, n: int = 1, value: str = "cnt", strategy: str = "auto") -> DataFrame:
    """Ranked images (group_rank, image_rank, xdim, ydim, zdim, slab, score) of a subset of a table."""
    s = Session.prepare(df, specs, row_key)
    cells = materialize(s.cube(s.bin(where, bins), bins, measures, strategy), "cube")
    scored = recommend.score_cube(cells, specs, bins, z_parts, value)
    return recommend.recommend(scored, m, n)


def pictures(session: Session, cells: DataFrame, bins: int, chosen: DataFrame, z_parts: int = 4) -> DataFrame:
    """PNG files of the chosen images only: cells of others are dropped before any pixel is made."""
    wanted = session.images(cells, bins, z_parts).join(chosen.select(*IMAGE), IMAGE, "left_semi")
    return render.render_png(diverging(wanted, bins).select(*IMAGE, "x", "y", *[F.col(c) for c in "rgb"]), bins)
