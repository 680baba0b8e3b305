"""Measures of the methods: balance, routing, colour shares, recall of planted patterns, timings."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubelens.storage import materialize, release


def unit_loads(routed: DataFrame) -> DataFrame:
    """(owner, owner_bin, rows): rows each unit receives in a round."""
    return routed.groupBy("owner", "owner_bin").agg(F.count("*").alias("rows"))


def axis_share(binned: DataFrame, bin_col: str, value: str) -> DataFrame:
    """(value, bins, rows): how many bins each value of an expression reaches into."""
    return binned.groupBy(F.expr(value).cast("string").alias("value")).agg(F.countDistinct(bin_col).alias("bins"), F.count("*").alias("rows"))


def area_by_color(pixels: DataFrame, bins: int, threshold: float = 0.5) -> DataFrame:
    """(image, red_area, blue_area): shares of an image's cells that are mostly red or blue; absent cells are blue."""
    size = float(bins * bins)
    red = F.sum((F.col("r") >= threshold).cast("int"))
    blue = F.sum((F.col("b") >= threshold).cast("int")) + (F.lit(bins * bins) - F.count("*"))
    return pixels.groupBy("xdim", "ydim", "zdim", "slab").agg((red / size).alias("red_area"), (blue / size).alias("blue_area"))


def recall_at(groups: DataFrame, planted: list[tuple[str, str]], m: int) -> float:
    """Share of planted axis pairs among the first m groups."""
    top = {tuple(sorted((r.xdim, r.ydim))) for r in groups.filter(F.col("group_rank") <= m).select("xdim", "ydim").collect()}
    return sum(tuple(sorted(p)) in top for p in planted) / max(len(planted), 1)


def timed(run: Callable[[], DataFrame]) -> float:
    """Seconds to compute all rows of a frame."""
    began = time.perf_counter()
    run().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def speedup(seconds: float, baseline: float) -> float:
    """Percent of the baseline's time that is saved."""
    return 100.0 * (1 - seconds / baseline)


def staged_times(rows: DataFrame, specs, bins: int, measures=(), owners: int | None = None) -> dict[str, float]:
    """Seconds of the parts of the owner-sliced strategy one after another, and of all of it pipelined.

    ``fill``: rows of all rounds routed and written; ``update``: units add up what was written
    and keep their slices; ``read_back``: cells of the kept slices are written; ``synchronous``:
    their sum; ``pipelined``: one job from rows to written cells; ``overlap``: the share of the
    synchronous time that it saves.
    """
    from cubelens.operators import cube
    from cubelens.plans.triples import plan_rounds

    plan, out = plan_rounds(len(specs), owners), {}
    rounds = cube.owned_by_round(plan)
    tables = []

    def part(name: str, frames: list[DataFrame]) -> list[DataFrame]:
        began = time.perf_counter()
        done = [materialize(d, name) for d in frames]
        out[name] = time.perf_counter() - began
        tables.extend(done)
        return done

    sent = part("fill", [cube.route(rows, specs, sorted(owned), measures) for owned in rounds])
    slices = part("update", [cube.update_units(d, owned, len(specs), bins, measures) for d, owned in zip(sent, rounds)])
    part("read_back", [cube.slices_to_cube(d, len(specs), bins, plan, measures) for d in slices])
    out["synchronous"] = out["fill"] + out["update"] + out["read_back"]
    part("pipelined", [cube.owner_slice(rows, specs, measures, bins, owners)])
    out["overlap"] = 1 - out["pipelined"] / out["synchronous"]
    for d in tables:
        release(d)
    return out


def units_times(make: Callable[[DataFrame, int], DataFrame], rows: DataFrame, units: list[int]) -> dict[int, float]:
    """Seconds by the number of tasks that may work at a time: the same written rows, read by and sent to as many."""
    dealt = materialize(rows.repartition(max(units)), "dealt")
    out = {k: timed(lambda k=k: make(dealt.coalesce(k), k)) for k in units}
    release(dealt)
    return out


def insert_share(ranked: DataFrame, new_rows: DataFrame, spec, bins: int, row_key: tuple[str, ...], total: int, fine_bits: int = 20) -> dict[str, float]:
    """Seconds to bin new rows by remembered bounds, to rank and bin all rows again, and the share of the first in the second."""
    from cubelens.operators import binning, insert
    from cubelens.operators.rank import build_ranks

    bounds = materialize(insert.capture_bounds(ranked, spec, total, fine_bits), "bounds")
    once = timed(lambda: insert.bin_inserts(new_rows, bounds, spec, bins, row_key)[0])
    both = ranked.drop(spec.rank).unionByName(new_rows.select(*[c for c in ranked.columns if c != spec.rank]))
    again = timed(lambda: binning.bin_by_rank(build_ranks(both, [spec], row_key), [spec], total + 1, bins))
    release(bounds)
    return {"insert": once, "rank_and_bin": again, "share": once / again}
