"""Queries q30 - q42: one cube by every strategy, other measures and arities."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import functions as F

from cubelens.operators import cube
from cubelens.queries import base as Q
from cubelens.sources import catalog as C

queries, oracles = {}, {}
_CENTS = ", CAST(sum(cents) AS BIGINT) AS cents"
_SQL = f"WITH {Q.cube_sql(Q.DIMS, Q.BINS, measures=_CENTS)} SELECT * FROM cube"


def _strategy(name, strategy, **options):
    queries[name] = lambda spark, sf: cube.build_cube(Q.binned(spark, sf, Q.DIMS, Q.BINS), Q.DIMS, Q.BINS, [C.CENTS], strategy, **options)
    oracles[name] = _SQL


_strategy("q30_cube_expand", "expand")
_strategy("q31_cube_explode", "explode")
_strategy("q32_cube_per_triple", "per_triple")
_strategy("q33_cube_partitioned", "per_triple", parts=2)
_strategy("q33b_cube_partitioned4", "per_triple", parts=4)
_strategy("q34_cube_owner_slice", "owner_slice")
_strategy("q34b_cube_staged", "owner_slice", staged=True, kernel="scan_per_triple")
_strategy("q34c_cube_by_triple", "by_triple")
_strategy("q35_cube_local_dense", "local_dense")
_strategy("q36_cube_salted", "owner_slice", replicas=3)
_strategy("q42_cube_rounds", "owner_slice", owners=4)
_strategy("q42b_cube_auto", "auto")


def q37_cube_pairs(spark, sf):
    return cube.build_pairs(Q.binned(spark, sf, Q.DIMS, Q.BINS), Q.DIMS, bins=Q.BINS)


oracles["q37_cube_pairs"] = f"WITH {Q.binned_sql(Q.DIMS, Q.BINS)} " + " UNION ALL ".join(f"SELECT {k} AS pair, {a.bin} AS b0, {b.bin} AS b1, count(*) AS cnt FROM binned GROUP BY 2, 3" for k, (a, b) in enumerate(combinations(Q.DIMS, 2)))


def q38_cube_sum_cents(spark, sf):
    """A signed measure on the log: sums of exact cents of changes, null changes left out."""
    specs = [C.LOG[k] for k in ("value", "gap_prev", "minute_of_day", "nth")]
    measure = C.MeasureSpec("delta", "CAST(round(value_delta * 100) AS BIGINT)")
    out = cube.build_cube(Q.binned(spark, sf, specs, Q.BINS, log=True), specs, Q.BINS, [measure], "owner_slice")
    return out.withColumn("delta", F.coalesce("delta", F.lit(0)))


oracles["q38_cube_sum_cents"] = f"WITH {Q.cube_sql([C.LOG[k] for k in ('value', 'gap_prev', 'minute_of_day', 'nth')], Q.BINS, True, ', CAST(coalesce(sum(CAST(round(value_delta * 100) AS BIGINT)), 0) AS BIGINT) AS delta')} SELECT * FROM cube"


def _float(name, strategy):
    queries[name] = lambda spark, sf: cube.build_cube(Q.binned(spark, sf, Q.DIMS, Q.BINS), Q.DIMS, Q.BINS, [C.PRICE_FLOAT, C.QUANTITY_DOUBLE], strategy).withColumns({"price": F.round("price", 3), "quantity": F.round("quantity", 3)})
    oracles[name] = f"WITH {Q.cube_sql(Q.DIMS, Q.BINS, measures=', round(sum(CAST(CAST(l_extendedprice AS FLOAT) AS DOUBLE)), 3) AS price, round(sum(l_quantity), 3) AS quantity')} SELECT * FROM cube"


_float("q39_cube_float", "local_dense")


def q40_cube_avg_minmax(spark, sf):
    return cube.build_extremes(Q.binned(spark, sf, Q.DIMS, Q.BINS), Q.DIMS, "l_quantity")


oracles["q40_cube_avg_minmax"] = f"WITH {Q.cube_sql(Q.DIMS, Q.BINS, measures=', sum(l_quantity) / count(l_quantity) AS avg, min(l_quantity) AS least, max(l_quantity) AS most')} SELECT * FROM cube"


def q41_marginals(spark, sf):
    return cube.build_marginals(Q.binned(spark, sf, Q.DIMS, Q.BINS), Q.DIMS)


oracles["q41_marginals"] = f"WITH {Q.binned_sql(Q.DIMS, Q.BINS)} " + " UNION ALL ".join(f"SELECT '{s.name}' AS dim, {s.bin} AS bin, count(*) AS cnt FROM binned GROUP BY 2" for s in Q.DIMS)

for _f in (q37_cube_pairs, q38_cube_sum_cents, q40_cube_avg_minmax, q41_marginals):
    queries[_f.__name__] = _f
