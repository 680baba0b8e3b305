"""Queries q70 - q79: the pictures that compare ways to bin, and the recommender, on the given tables."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import functions as F

from cubelens.dimension import DimensionSpec
from cubelens.functions import intensity as I
from cubelens.operators import baselines, binning, cube, image
from cubelens.operators.rank import build_ranks
from cubelens.queries import base as Q
from cubelens.sources import catalog as C

queries, oracles = {}, {}
S, L = C.STAR, C.LOG


def _pair(name, x, y, bins, log=False):
    """Pixels of one equal-population picture of two dimensions."""

    def run(spark, sf):
        pairs = cube.build_pairs(Q.binned(spark, sf, [x, y], bins, log), [x, y], bins=bins)
        out = I.diverging(image.pair_images(pairs, [x, y]), bins)
        return out.select("x", "y", "v", F.round("r", 9).alias("r"), F.round("b", 9).alias("b"))

    queries[name] = run
    oracles[name] = (
        f"WITH {Q.binned_sql([x, y], bins, log)}, c AS (SELECT {x.bin} AS x, {y.bin} AS y, count(*) AS v FROM binned GROUP BY 1, 2), s AS (SELECT sum(v) / {float(bins * bins)} AS s FROM c) "
        "SELECT x, y, v, round(CASE WHEN v > s THEN least(1.0::DOUBLE, v / s - 1) ELSE 0 END, 9) AS r, round(CASE WHEN v <= s THEN 1 - v / s ELSE 0 END, 9) AS b FROM c, s"
    )


_pair("q70_discount_price", S["price"], S["discount"], 16)
_pair("q70b_discount_price_coarse", S["price"], S["discount"], 8)
_pair("q70c_revenue_price", S["price"], S["net_revenue"], 16)
_pair("q73_discount_by_time", S["ship_time"], S["discount_by_time"], 16)
_pair("q74_gap_by_week_time", L["week_time"], L["gap_prev"], 16, True)

_LOW, _HIGH = (0, 0), (60000, 40)


def _flat(name, where, outliers, bins=16):
    """Equal-width picture of price and quantity in integer units, coloured by its marginals; clipped by hand or with outliers left in."""
    extra = " UNION ALL SELECT CAST(max(l_extendedprice * 1000) AS BIGINT), 1 FROM lineitem" if outliers else ""
    rows = f"SELECT CAST(floor(l_extendedprice) AS BIGINT) AS p, CAST(l_quantity AS BIGINT) AS q FROM lineitem {where}{extra}"

    def run(spark, sf):
        d = C.table(spark, sf, "lineitem")
        if where:
            d = baselines.clip_rows(d, {"l_extendedprice": (_LOW[0], _HIGH[0]), "l_quantity": (_LOW[1], _HIGH[1])})
        d = d.select(F.floor("l_extendedprice").alias("p"), F.col("l_quantity").cast("long").alias("q"))
        if outliers:
            d = d.unionByName(C.table(spark, sf, "lineitem").agg((F.max(F.col("l_extendedprice") * 1000)).cast("long").alias("p")).withColumn("q", F.lit(1).cast("long")))
        e = d.agg(F.min("p"), F.max("p"), F.min("q"), F.max("q")).first()
        at = lambda c, lo, hi: F.least(F.expr(f"(({c} - {lo}) * {bins}) div {max(hi - lo, 1)}"), F.lit(bins - 1)).cast("int")
        cells = d.groupBy(at("p", e[0], e[1]).alias("x"), at("q", e[2], e[3]).alias("y")).agg(F.count("*").alias("v"))
        cells = cells.select(F.lit("price").alias("xdim"), F.lit("quantity").alias("ydim"), F.lit("").alias("zdim"), F.lit(0).alias("slab"), "x", "y", "v")
        return I.marginal_expected(cells).select("x", "y", "v", F.round("r", 9).alias("r"), F.round("b", 9).alias("b"))

    queries[name] = run
    oracles[name] = (
        f"WITH d AS ({rows}), e AS (SELECT min(p) AS p0, greatest(max(p) - min(p), 1) AS pw, min(q) AS q0, greatest(max(q) - min(q), 1) AS qw FROM d), "
        f"c AS (SELECT CAST(least(((p - p0) * {bins}) // pw, {bins - 1}) AS INT) AS x, CAST(least(((q - q0) * {bins}) // qw, {bins - 1}) AS INT) AS y, count(*) AS v FROM d, e GROUP BY 1, 2), "
        "m AS (SELECT x, y, v, CAST(sum(v) OVER (PARTITION BY x) * sum(v) OVER (PARTITION BY y) AS DOUBLE) / sum(v) OVER () AS s FROM c) "
        "SELECT x, y, v, round(CASE WHEN v > s THEN least(1.0::DOUBLE, v / s - 1) ELSE 0 END, 9) AS r, round(CASE WHEN v <= s THEN 1 - v / s ELSE 0 END, 9) AS b FROM m"
    )


_flat("q71_equal_width_clipped", f"WHERE l_extendedprice BETWEEN {_LOW[0]} AND {_HIGH[0]} AND l_quantity BETWEEN {_LOW[1]} AND {_HIGH[1]}", False)
_flat("q72_equal_width_outliers", "", True)


def q75_packed_week_time(spark, sf):
    """Day and minute packed into one number: the unused ranges between days stay empty bins."""
    d = C.activity_log(spark, sf).withColumn("packed", F.expr("dow * 10000 + minute_of_day"))
    return d.groupBy(F.least(F.expr("(packed * 64) div 61440"), F.lit(63)).cast("int").alias("b")).agg(F.count("*").alias("n"))


oracles["q75_packed_week_time"] = f"WITH f AS ({C.LOG_DUCK}) SELECT CAST(least(((dow * 10000 + minute_of_day) * 64) // 61440, 63) AS INT) AS b, count(*) AS n FROM f GROUP BY 1"

_GEO = [S["cust_geo"], S["total_price"], S["order_time"]]


def q76_geo_slabs(spark, sf):
    c = cube.build_cube(Q.binned(spark, sf, _GEO, 16), _GEO, 16, [], "owner_slice")
    out = I.diverging(image.slab_images(c, _GEO, 16, 4, z_roles="2"), 16)
    return out.select("slab", "x", "y", "v", F.round("r", 9).alias("r"), F.round("b", 9).alias("b"))


oracles["q76_geo_slabs"] = (
    f"WITH {Q.binned_sql(_GEO, 16)}, c AS (SELECT CAST((b_order_time * 4) // 16 AS INT) AS slab, b_cust_geo AS x, b_total_price AS y, count(*) AS v FROM binned GROUP BY ALL), s AS (SELECT slab, sum(v) / 256.0::DOUBLE AS s FROM c GROUP BY slab) "
    "SELECT slab, x, y, v, round(CASE WHEN v > s THEN least(1.0::DOUBLE, v / s - 1) ELSE 0 END, 9) AS r, round(CASE WHEN v <= s THEN 1 - v / s ELSE 0 END, 9) AS b FROM c JOIN s USING (slab)"
)


def q77_geo_categorical(spark, sf):
    d = baselines.bin_categorical(C.order_star(spark, sf), "c_nationkey", "x")
    e = d.agg(F.min(F.floor("o_totalprice")), F.max(F.floor("o_totalprice"))).first()
    y = F.least(F.expr(f"((CAST(floor(o_totalprice) AS BIGINT) - {e[0]}) * 16) div {e[1] - e[0]}"), F.lit(15)).cast("int")
    return d.groupBy("x", y.alias("y")).agg(F.count("*").alias("v"))


oracles["q77_geo_categorical"] = (
    f"WITH f AS ({C.STAR_SQL}), n AS (SELECT c_nationkey, row_number() OVER (ORDER BY c_nationkey) - 1 AS x FROM (SELECT DISTINCT c_nationkey FROM f)), g AS (SELECT x, CAST(floor(o_totalprice) AS BIGINT) AS p FROM f JOIN n USING (c_nationkey)), "
    "e AS (SELECT min(p) AS lo, max(p) AS hi FROM g) SELECT CAST(x AS INT) AS x, CAST(least(((p - lo) * 16) // (hi - lo), 15) AS INT) AS y, count(*) AS v FROM g, e GROUP BY 1, 2"
)

_THIRTEEN = C.STAR_DIMS[:13]


def q79_pairs13(spark, sf):
    """All 78 two-dimensional aggregates of 13 dimensions at 100 bins in a single pass."""
    return cube.build_pairs(Q.bins_only(spark, sf, _THIRTEEN, 100), _THIRTEEN, bins=100)


oracles["q79_pairs13"] = f"WITH {Q.binned_sql(_THIRTEEN, 100)} " + " UNION ALL ".join(f"SELECT {k} AS pair, {a.bin} AS b0, {b.bin} AS b1, count(*) AS cnt FROM binned GROUP BY 2, 3" for k, (a, b) in enumerate(combinations(_THIRTEEN, 2)))

_COORDS = [DimensionSpec(f"e{i}", (f"e{i}",)) for i in range(6)]


def q79c_coordinates(spark, sf):
    """Array elements as dimensions: cubes of six coordinates."""
    d = C.table(spark, sf, "embeddings").select("vec_id", *[F.get("embedding", F.lit(i)).alias(f"e{i}") for i in range(6)])
    r = build_ranks(d, _COORDS, ("vec_id",))
    return cube.build_cube(binning.bin_by_rank(r, _COORDS, r.count(), 4), _COORDS, 4, [], "owner_slice")


_KEY = "md5(concat_ws(':', '{0}', CAST(vec_id AS VARCHAR))), vec_id"
oracles["q79c_coordinates"] = (
    "WITH f AS (SELECT vec_id, " + ", ".join(f"embedding[{i + 1}] AS e{i}" for i in range(6)) + " FROM embeddings), binned AS (SELECT vec_id, "
    + ", ".join(f"CAST((row_number() OVER (ORDER BY e{i}, {_KEY.format(f'e{i}')}) - 1) // ((count(*) OVER () + 3) // 4) AS INT) AS b_e{i}" for i in range(6))
    + " FROM f) "
    + " UNION ALL ".join(f"SELECT {k} AS triple, b_e{a} AS b0, b_e{b} AS b1, b_e{c} AS b2, count(*) AS cnt FROM binned GROUP BY 2, 3, 4" for k, (a, b, c) in enumerate(combinations(range(6), 3)))
)

_DOCS = [DimensionSpec("quality", ("quality",)), DimensionSpec("n_chars", ("n_chars",)), DimensionSpec("lang_by_size", ("lang", "n_chars"))]


def q79d_null_population(spark, sf):
    """Unlabelled documents are a population of their own at the low end of the axis."""
    d = C.table(spark, sf, "documents").select("doc_id", "lang", "n_chars").join(C.table(spark, sf, "labels"), "doc_id", "left")
    r = build_ranks(d, _DOCS, ("doc_id",))
    return binning.bin_by_rank(r, _DOCS, r.count(), 16).select("doc_id", *[F.col(s.bin).cast("int").alias(s.bin) for s in _DOCS])


oracles["q79d_null_population"] = (
    "SELECT doc_id, "
    + ", ".join(f"CAST((row_number() OVER (ORDER BY {s.order_sql()}, md5(concat_ws(':', '{s.name}', CAST(doc_id AS VARCHAR))), doc_id) - 1) // ((count(*) OVER () + 15) // 16) AS INT) AS {s.bin}" for s in _DOCS)
    + " FROM documents LEFT JOIN labels USING (doc_id)"
)

for _f in (q79c_coordinates, q79d_null_population, q75_packed_week_time, q76_geo_slabs, q77_geo_categorical, q79_pairs13):
    queries[_f.__name__] = _f
