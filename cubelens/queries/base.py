"""Prepared tables that queries share, and the SQL text they are checked with."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cubelens.dimension import DimensionSpec, tie_sql
from cubelens.operators import binning, cuts
from cubelens.operators.rank import build_ranks
from cubelens.plans.triples import triples_of
from cubelens.sources import catalog as C
from cubelens.storage import materialize, passing_shuffles, release, small_scans

#: Dimensions and bins of the cube queries.
DIMS = [C.STAR[k] for k in ("price", "net_revenue", "quantity", "discount", "ship_time", "unit_price")]
BINS = 8

_kept: dict = {}


def once(spark: SparkSession, key: tuple, make) -> object:
    """Written tables are reused inside a session, as an analyst reuses ranks."""
    key = (spark.sparkContext.applicationId, *key)
    if key not in _kept:
        _kept[key] = make()
    return _kept[key]


def facts(spark: SparkSession, sf_dir: str, log: bool = False) -> DataFrame:
    return C.activity_log(spark, sf_dir) if log else C.order_star(spark, sf_dir)


def ranked(spark: SparkSession, sf_dir: str, specs: list[DimensionSpec], log: bool = False) -> tuple[DataFrame, int]:
    def make():
        d = build_ranks(facts(spark, sf_dir, log), specs, C.LOG_KEY if log else C.STAR_KEY)
        return d, d.count()

    return once(spark, ("ranked", sf_dir, log, *[s.name for s in specs]), make)


def binned(spark: SparkSession, sf_dir: str, specs: list[DimensionSpec], bins: int, log: bool = False, rule: str = "ceil") -> DataFrame:
    def make():
        d, n = ranked(spark, sf_dir, specs, log)
        return materialize(binning.bin_by_rank(d, specs, n, bins, rule), "binned")

    return once(spark, ("binned", sf_dir, log, bins, rule, *[s.name for s in specs]), make)


def bins_only(spark: SparkSession, sf_dir: str, specs: list[DimensionSpec], bins: int, log: bool = False, rule: str = "ceil") -> DataFrame:
    """The bins of ``binned`` and no other column: no ranks and no wide rows are written, so that the disk holds a few bytes a row and dimension."""

    def make():
        key = C.LOG_KEY if log else C.STAR_KEY
        whole = facts(spark, sf_dir, log)
        used = set(key) | {w for s in specs for k in s.keys for w in re.findall(r"\w+", k)}
        columns = [c for c in whole.columns if c in used]
        if not cuts.comparable(whole, specs):
            return binned(spark, sf_dir, specs, bins, log, rule).select(*[s.bin for s in specs])
        base = whole.select(*columns) if log else C.order_star_slices(spark, sf_dir, columns)
        with passing_shuffles(spark):
            rows = cuts.bin_rows(base, specs, key, bins, rule)
            with small_scans(spark):
                out = materialize(rows, "bins")
        release(rows)
        return out

    return once(spark, ("bins", sf_dir, log, bins, rule, *[s.name for s in specs]), make)


def key_columns(log: bool = False) -> list:
    return [F.col(k) for k in (C.LOG_KEY if log else C.STAR_KEY)]


# SQL text -------------------------------------------------------------------------------


def facts_sql(log: bool = False, extra: str = "") -> str:
    return f"SELECT *{extra} FROM ({C.LOG_DUCK if log else C.STAR_SQL})"


def ranked_sql(specs: list[DimensionSpec], log: bool = False) -> str:
    key = C.LOG_KEY if log else C.STAR_KEY
    ranks = ", ".join(f"row_number() OVER (ORDER BY {s.order_sql()}, {tie_sql(s, key)}) - 1 AS {s.rank}" for s in specs)
    return f"facts AS ({facts_sql(log)}), ranked AS (SELECT *, {ranks}, count(*) OVER () AS n FROM facts)"


def binned_sql(specs: list[DimensionSpec], bins: int, log: bool = False, rule: str = "ceil", where: str = "") -> str:
    place = (lambda s: f"({s.rank} * {bins}) // n") if rule == "proportional" else (lambda s: f"{s.rank} // ((n + {bins - 1}) // {bins})")
    cols = ", ".join(f"CAST({place(s)} AS INT) AS {s.bin}" for s in specs)
    return ranked_sql(specs, log) + f", binned AS (SELECT *, {cols} FROM ranked {where})"


def cube_sql(specs: list[DimensionSpec], bins: int, log: bool = False, measures: str = "", arity: int = 3) -> str:
    """... , cube AS (triple, b0, b1, b2, cnt, measures)."""
    parts = []
    for k, t in enumerate(triples_of(len(specs))):
        cols = ", ".join(f"{specs[d].bin} AS b{i}" for i, d in enumerate(t))
        parts.append(f"SELECT {k} AS triple, {cols}, count(*) AS cnt{measures} FROM binned GROUP BY {', '.join(specs[d].bin for d in t)}")
    return binned_sql(specs, bins, log) + ", cube AS (" + " UNION ALL ".join(parts) + ")"


def images_sql(specs: list[DimensionSpec], bins: int, parts: int, log: bool = False, measures: str = "", value: str = "cnt") -> str:
    """... , cells AS (xdim, ydim, zdim, slab, x, y, v)."""
    rows = []
    for k, t in enumerate(triples_of(len(specs))):
        for z in range(3):
            x, y = (i for i in range(3) if i != z)
            rows.append(f"({k}, {z}, '{specs[t[x]].name}', '{specs[t[y]].name}', '{specs[t[z]].name}')")
    b = lambda k: f"CASE z WHEN {k} THEN"
    return (
        cube_sql(specs, bins, log, measures)
        + f", roles(t, z, xdim, ydim, zdim) AS (VALUES {', '.join(rows)}), cells AS (SELECT xdim, ydim, zdim, "
        + f"CAST((CASE z WHEN 0 THEN b0 WHEN 1 THEN b1 ELSE b2 END * {parts}) // {bins} AS INT) AS slab, CASE z WHEN 0 THEN b1 ELSE b0 END AS x, CASE z WHEN 2 THEN b1 ELSE b2 END AS y, "
        + f"CAST(sum({value}) AS BIGINT) AS v FROM cube JOIN roles ON triple = t GROUP BY ALL)"
    )


def scores_sql(bins: int) -> str:
    """... , scored AS (xdim, ydim, zdim, slab, total, expected, score)."""
    size = float(bins * bins)
    return (
        f", totals AS (SELECT xdim, ydim, zdim, slab, sum(v) AS total, sum(v) / {size} AS expected FROM cells GROUP BY ALL)"
        f", scored AS (SELECT xdim, ydim, zdim, slab, any_value(total) AS total, any_value(expected) AS expected, sum(CASE WHEN expected > 0 AND v > expected THEN least(1.0::DOUBLE, v / expected - 1) ELSE 0 END) / {size} AS score"
        " FROM cells JOIN totals USING (xdim, ydim, zdim, slab) GROUP BY xdim, ydim, zdim, slab)"
    )
