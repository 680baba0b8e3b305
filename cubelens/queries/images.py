"""Queries q50 - q62: images, colours, scores, recommendation, pictures, drilling."""

from __future__ import annotations

from pyspark.sql import functions as F

from cubelens.functions import intensity as I
from cubelens.operators import cube, image, recommend, render
from cubelens.queries import base as Q
from cubelens.storage import materialize

queries, oracles = {}, {}
PARTS, B = 4, Q.BINS
_CELLS = Q.images_sql(Q.DIMS, B, PARTS)
_SCORED = _CELLS + Q.scores_sql(B)
KEYS = "xdim, ydim, zdim, slab"


def cells(spark, sf):
    def make():
        c = cube.build_cube(Q.binned(spark, sf, Q.DIMS, B), Q.DIMS, B, [], "local_dense")
        return materialize(image.slab_images(c, Q.DIMS, B, PARTS), "cells")

    return Q.once(spark, ("cells", sf), make)


def scored(spark, sf):
    return Q.once(spark, ("scored", sf), lambda: materialize(recommend.score_images(cells(spark, sf), B), "scored"))


def register(sql=None):
    def keep(fn):
        queries[fn.__name__] = fn
        if sql:
            oracles[fn.__name__] = sql
        return fn

    return keep


@register(f"WITH {_CELLS} SELECT * FROM cells")
def q50_slab_images(spark, sf):
    c = cube.build_cube(Q.binned(spark, sf, Q.DIMS, B), Q.DIMS, B, [], "local_dense")
    return image.slab_images(c, Q.DIMS, B, PARTS)


@register(
    f"WITH {_CELLS}, t AS (SELECT {KEYS}, sum(v) / {float(B * B)} AS expected FROM cells GROUP BY ALL) SELECT {KEYS}, x, y, v, expected, "
    "round(CASE WHEN v > expected THEN least(1.0::DOUBLE, v / expected - 1) ELSE 0 END, 9) AS r, CAST(0 AS DOUBLE) AS g, round(CASE WHEN v <= expected THEN 1 - v / expected ELSE 0 END, 9) AS b, false AS degenerate FROM cells JOIN t USING (xdim, ydim, zdim, slab)"
)
def q51_intensity_diverging(spark, sf):
    return I.diverging(cells(spark, sf), B).withColumns({"r": F.round("r", 9), "b": F.round("b", 9)})


@register(
    f"WITH {_CELLS}, k AS (SELECT DISTINCT {KEYS} FROM cells), full_ AS (SELECT {KEYS}, CAST(c // {B} AS INT) AS x, CAST(c % {B} AS INT) AS y FROM k, (SELECT unnest(range({B * B})) AS c)), "
    f"d AS (SELECT {KEYS}, x, y, coalesce(v, 0) AS v FROM full_ LEFT JOIN cells USING ({KEYS}, x, y)), p AS (SELECT {KEYS}, quantile_cont(CAST(v AS DOUBLE), 0.05) AS lo, quantile_cont(CAST(v AS DOUBLE), 0.95) AS hi FROM d GROUP BY ALL) "
    f"SELECT {KEYS}, x, y, v, round(CASE WHEN hi > lo THEN least(1, greatest(0, (v - lo) / (hi - lo))) ELSE 0 END, 9) AS gray FROM d JOIN p USING ({KEYS})"
)
def q52_intensity_gray(spark, sf):
    return I.grayscale(cells(spark, sf), B).withColumn("gray", F.round("gray", 9))


@register(
    f"WITH {_CELLS}, t AS (SELECT {KEYS}, sum(v) / {float(B * B)} AS expected, max(v) AS top FROM cells GROUP BY ALL) SELECT {KEYS}, x, y, v, expected, "
    f"round(CASE WHEN v > expected THEN (v - expected) / (top - expected) ELSE 0 END, 9) AS r, round(CASE WHEN v <= expected THEN 1 - v / expected ELSE 0 END, 9) AS b FROM cells JOIN t USING ({KEYS})"
)
def q53_intensity_max(spark, sf):
    return I.max_scaled(cells(spark, sf), B).withColumns({"r": F.round("r", 9), "b": F.round("b", 9)})


@register(
    f"WITH {_CELLS}, rx AS (SELECT {KEYS}, x, sum(v) AS rx FROM cells GROUP BY ALL), cy AS (SELECT {KEYS}, y, sum(v) AS cy FROM cells GROUP BY ALL), t AS (SELECT {KEYS}, sum(v) AS t FROM cells GROUP BY ALL), "
    f"e AS (SELECT {KEYS}, x, y, v, CAST(rx * cy AS DOUBLE) / t AS expected FROM cells JOIN rx USING ({KEYS}, x) JOIN cy USING ({KEYS}, y) JOIN t USING ({KEYS})) "
    f"SELECT {KEYS}, x, y, v, round(expected, 9) AS expected, round(CASE WHEN v > expected THEN least(1.0::DOUBLE, v / expected - 1) ELSE 0 END, 9) AS r, round(CASE WHEN v <= expected THEN 1 - v / expected ELSE 0 END, 9) AS b FROM e"
)
def q54_intensity_marginal(spark, sf):
    return I.marginal_expected(cells(spark, sf)).withColumns({k: F.round(k, 9) for k in ("expected", "r", "b")})


@register(
    f"WITH {Q.binned_sql(Q.DIMS[2:3], 12)}, c AS (SELECT b_quantity AS bin, count(*) AS n FROM binned GROUP BY 1) SELECT bin, round(CAST(coalesce(sum(n) OVER (ORDER BY bin ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS DOUBLE) / sum(n) OVER (), 9) AS start, round(CAST(n AS DOUBLE) / sum(n) OVER (), 9) AS width FROM c"
)
def q55_layout_population(spark, sf):
    out = I.population_layout(Q.binned(spark, sf, Q.DIMS[2:3], 12), "b_quantity")
    return out.select("bin", F.round("start", 9).alias("start"), F.round("width", 9).alias("width"))


@register(f"WITH {_SCORED} SELECT {KEYS}, CAST(total AS BIGINT) AS total, expected, round(score, 9) AS score, expected <= 0 AS degenerate FROM scored")
def q56_score_images(spark, sf):
    return recommend.score_images(cells(spark, sf), B).withColumn("score", F.round("score", 9))


def groups_sql(order: str = "DESC") -> str:
    return f", grouped AS (SELECT xdim, ydim, sum(score) AS score, count(*) AS images FROM scored GROUP BY ALL), ordered AS (SELECT *, CAST(row_number() OVER (ORDER BY round(score, 9) {order}, xdim, ydim) AS INT) AS group_rank FROM grouped)"


@register(f"WITH {_SCORED}{groups_sql()} SELECT xdim, ydim, round(score, 9) AS score, images, group_rank FROM ordered")
def q57_score_groups(spark, sf):
    return recommend.score_groups(scored(spark, sf)).withColumn("score", F.round("score", 9))


def recommend_sql(m: int, n: int, order: str = "DESC") -> str:
    return f"{groups_sql(order)}, inside AS (SELECT group_rank, CAST(row_number() OVER (PARTITION BY s.xdim, s.ydim ORDER BY round(s.score, 9) DESC, zdim, slab) AS INT) AS image_rank, s.xdim, s.ydim, zdim, slab, round(s.score, 9) AS score FROM scored s JOIN ordered o ON s.xdim = o.xdim AND s.ydim = o.ydim WHERE group_rank <= {m}) SELECT * FROM inside WHERE image_rank <= {n}"


@register(f"WITH {_SCORED}{recommend_sql(5, 3)}")
def q58_recommend(spark, sf):
    return recommend.recommend(scored(spark, sf), 5, 3).withColumn("score", F.round("score", 9))


@register(
    f"WITH {_SCORED}, a AS (SELECT *, row_number() OVER (PARTITION BY xdim, ydim ORDER BY round(score, 9) DESC, zdim, slab) AS appearance FROM scored) "
    f"SELECT {KEYS}, round(score, 9) AS score, CAST(appearance AS INT) AS appearance, CAST(row_number() OVER (ORDER BY appearance, round(score, 9) DESC, {KEYS}) AS INT) AS priority FROM a"
)
def q59_demotion(spark, sf):
    return recommend.prioritise(scored(spark, sf)).select("xdim", "ydim", "zdim", "slab", F.round("score", 9).alias("score"), "appearance", "priority")


@register()
def q61_render_png(spark, sf):
    chosen = recommend.recommend(scored(spark, sf), 3, 2)
    wanted = cells(spark, sf).join(chosen.select(*I.IMAGE), I.IMAGE, "left_semi")
    return render.render_png(I.diverging(wanted, B), B, scale=4)


@register(f"WITH {Q.binned_sql(Q.DIMS, B)} SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, cents FROM binned WHERE b_quantity = 7 AND b_unit_price = 0 AND b_ship_time BETWEEN 2 AND 3")
def q62_drill_down(spark, sf):
    return image.drill(Q.binned(spark, sf, Q.DIMS, B), {"b_quantity": (7, 7), "b_unit_price": (0, 0), "b_ship_time": (2, 3)}).select(*Q.key_columns())


def _heuristic(name, expression, empty):
    queries[f"q63_heuristic_{name}"] = lambda spark, sf: recommend.score_images(cells(spark, sf), B, heuristic=name).select("xdim", "ydim", "zdim", "slab", F.round("score", 7).alias("score"))
    oracles[f"q63_heuristic_{name}"] = f"WITH {_CELLS}{Q.scores_sql(B)} SELECT {KEYS}, round((sum({expression}) + ({empty}) * ({B * B} - count(*))) / {float(B * B)}, 7) AS score FROM cells JOIN totals USING ({KEYS}) GROUP BY {KEYS}"


_heuristic("blue", "CASE WHEN v <= expected THEN 1 - v / expected ELSE 0 END", "1")
_heuristic("chi_square", "(v - expected) * (v - expected) / expected", "any_value(expected)")
_heuristic("information", "CASE WHEN v > 0 THEN v / expected * ln(v / expected) ELSE 0 END", "0")
