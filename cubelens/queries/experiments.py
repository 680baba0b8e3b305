"""Queries of the sizes, sweeps and measures of the experiments, and of workflow steps that have no query elsewhere."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cubelens.dimension import DimensionSpec
from cubelens.functions import intensity as I
from cubelens.operators import binning, cube, image, insert, metrics, rank, recommend, render
from cubelens.operators.rank import build_ranks
from cubelens.plans import cost
from cubelens.plans import triples as T
from cubelens.queries import base as Q
from cubelens.queries import images as M
from cubelens.queries.images import groups_sql
from cubelens.queries.plan import ROWS_SQL, plan_sql, with_rows
from cubelens.sources import catalog as C
from cubelens.storage import materialize
from cubelens.streaming.streams import scratch

queries, oracles = {}, {}
S, L = C.STAR, C.LOG
KEY = ", ".join(C.STAR_KEY)


def q(sql=None):
    def keep(fn):
        queries[fn.__name__] = fn
        if sql:
            oracles[fn.__name__] = sql
        return fn

    return keep


def _beside_rows(sql: str) -> str:
    return f"SELECT x.*, rows FROM ({sql}) x, {ROWS_SQL}"


# Ranks kept and reused ------------------------------------------------------------------

_KEPT = [S["price"], S["quantity"], S["discount_by_time"]]
_SOME = [S["quantity"], S["discount_by_time"]]


@q(f"WITH {Q.binned_sql(_SOME, 16)} SELECT {KEY}, {', '.join(s.bin for s in _SOME)} FROM binned")
def q02b_augmented_reuse(spark, sf):
    """Ranks are written beside the rows, read again, and binned for fewer dimensions without ranking."""
    d, n = Q.ranked(spark, sf, _KEPT)
    path = Q.once(spark, ("augmented", sf), lambda: scratch(spark, "augmented"))
    rank.write_augmented(d, path, _KEPT[0].rank)
    out = binning.bin_by_rank(rank.read_augmented(spark, path), _SOME, n, 16)
    return out.select(*Q.key_columns(), *[F.col(s.bin).cast("int").alias(s.bin) for s in _SOME])


_SKETCHED = [S["price"], S["total_price"], S["quantity"]]


@q(
    f"WITH {Q.ranked_sql(_SKETCHED)} "
    + " UNION ALL ".join(
        f"SELECT '{s.name}' AS dim, count(*) AS buckets, max(c) <= 1.5 * sum(c) / 16 AND min(c) >= 0.5 * sum(c) / 16 AS even, bool_and(hi <= coalesce(nxt, hi)) AS ordered FROM "
        f"(SELECT b, count(*) AS c, max(v) AS hi, lead(min(v)) OVER (ORDER BY b) AS nxt FROM (SELECT {s.keys[0]} AS v, ({s.rank} * 16) // n AS b FROM ranked) GROUP BY b)"
        for s in _SKETCHED
    )
)
def q02c_sketch_buckets(spark, sf):
    """Buckets from quantile sketches, without any sort: all used, nearly even, in the order of the values; heavy values spread."""
    d = rank.build_fine_buckets(Q.facts(spark, sf), _SKETCHED, C.STAR_KEY, 4)
    cells = F.explode(F.array(*[F.struct(F.lit(s.name).alias("dim"), F.col(s.rank).alias("b"), s.label().alias("v")) for s in _SKETCHED])).alias("x")
    per = d.select(cells).groupBy("x.dim", "x.b").agg(F.count("*").alias("c"), F.min("x.v").alias("lo"), F.max("x.v").alias("hi"))
    after = F.lead("lo").over(Window.partitionBy("dim").orderBy("b"))  # sixteen buckets a dimension
    per = per.withColumn("nxt", after)
    even = (F.max("c") <= 1.5 * F.sum("c") / 16) & (F.min("c") >= 0.5 * F.sum("c") / 16)
    return per.groupBy("dim").agg(F.count("*").alias("buckets"), even.alias("even"), F.min(F.col("hi") <= F.coalesce("nxt", "hi")).alias("ordered"))


_MONTH = "l_shipdate >= TIMESTAMP '1995-03-01' AND l_shipdate < TIMESTAMP '1995-04-01'"
_PAIR = [S["price"], S["discount"]]


@q(f"WITH {Q.ranked_sql(_PAIR)}, m AS (SELECT {KEY}, {', '.join(f'row_number() OVER (ORDER BY {s.rank}) - 1 AS p{i}' for i, s in enumerate(_PAIR))}, count(*) OVER () AS m FROM ranked WHERE {_MONTH}) SELECT {KEY}, {', '.join(f'CAST(p{i} // ((m + 15) // 16) AS INT) AS {s.bin}' for i, s in enumerate(_PAIR))} FROM m")
def q08c_small_subset(spark, sf):
    """A month of rows is too small for 256 fine buckets: its ranks are ordered instead."""
    d, n = Q.ranked(spark, sf, _PAIR)
    out = binning.bin_auto(d.filter(_MONTH), _PAIR, n, 16, 8)
    return out.select(*Q.key_columns(), *[F.col(s.bin).cast("int").alias(s.bin) for s in _PAIR])


# Inserts --------------------------------------------------------------------------------

_OLD_TAIL = "epoch_us(ts) <= (SELECT quantile_disc(epoch_us(ts), 0.99) FROM events)"


@q(
    f"WITH old AS (SELECT event_id, ts, row_number() OVER (ORDER BY ts, md5(concat_ws(':', 'ts', CAST(event_id AS VARCHAR))), event_id) - 1 AS rk FROM events WHERE {_OLD_TAIL}), "
    "h AS (SELECT CAST(rk >> greatest(0, CAST(ceil(log2((SELECT count(*) FROM old))) AS INT) - 8) AS INT) AS bucket, count(*) AS cnt, arg_min(ts, rk) AS first_ts FROM old GROUP BY 1), "
    f"new AS (SELECT event_id, ts, coalesce((SELECT max(bucket) FROM h WHERE first_ts <= e.ts), 0) AS bucket FROM events e WHERE NOT ({_OLD_TAIL})), "
    "a AS (SELECT bucket, CAST(sum(c) AS BIGINT) AS cnt FROM (SELECT bucket, cnt AS c FROM h UNION ALL SELECT bucket, count(*) FROM new GROUP BY 1) GROUP BY 1), "
    "p AS (SELECT bucket, coalesce(sum(cnt) OVER (ORDER BY bucket ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) // (((SELECT count(*) FROM events) + 15) // 16) AS bin FROM a) "
    "SELECT event_id, CAST(bin AS INT) AS b_ts FROM new JOIN p USING (bucket)"
)
def q20b_insert_tail(spark, sf):
    """The last hundredth of the time axis arrives as a batch: all of it lies above the first keys of the last bucket."""
    e, spec = C.table(spark, sf, "events").withColumn("us_", F.unix_micros(F.col("ts").cast("timestamp"))), L["ts"]
    cut = e.agg(F.expr("percentile_disc(0.99) WITHIN GROUP (ORDER BY us_)")).first()[0] or 0
    old = build_ranks(e.filter(F.col("us_") <= cut), [spec], C.LOG_KEY)
    bounds = insert.capture_bounds(old, spec, old.count(), 8)
    out, _ = insert.bin_inserts(e.filter(F.col("us_") > cut), bounds, spec, 16, C.LOG_KEY)
    return out.select("event_id", F.col("b_ts").cast("int").alias("b_ts"))


_OLD = "l_linenumber <= 5"


@q(
    f"WITH facts AS (SELECT * FROM ({C.STAR_SQL}) WHERE {_OLD}), r AS (SELECT l_quantity AS v, row_number() OVER (ORDER BY l_quantity, {Q.tie_sql(S['quantity'], C.STAR_KEY)}) - 1 AS rk, count(*) OVER () AS n FROM facts), "
    "h AS (SELECT CAST(rk >> greatest(0, CAST(ceil(log2(n)) AS INT) - 8) AS INT) AS bucket, arg_min(v, rk) AS first_v FROM r GROUP BY 1), "
    f"k AS (SELECT l_quantity AS v, count(*) AS n FROM lineitem WHERE NOT ({_OLD}) GROUP BY 1), g AS (SELECT v, n, (SELECT max(first_v) FROM h WHERE first_v <= k.v) AS f FROM k) "
    "SELECT v, n, CAST(coalesce((SELECT min(bucket) FROM h WHERE first_v = f), 0) AS INT) AS lo, CAST(coalesce((SELECT max(bucket) FROM h WHERE first_v = f), 0) AS INT) AS hi, true AS inside FROM g"
)
def q20c_insert_runs(spark, sf):
    """A value that owns several buckets: new rows with it are spread over exactly these."""
    d, spec = Q.facts(spark, sf), S["quantity"]
    old = build_ranks(d.filter(_OLD), [spec], C.STAR_KEY)
    total = old.count()
    bounds = materialize(insert.capture_bounds(old, spec, total, 8), "bounds")
    new = d.filter(f"NOT ({_OLD})")
    runs = insert.bucket_runs(new, bounds, spec).select(F.col("k.k0").alias("v"), "run.lo", "run.hi")
    rows = new.select(F.col("l_quantity").alias("v"), F.pmod(F.xxhash64(F.lit(spec.name), *Q.key_columns()), F.lit(1 << 20)).alias("h"))
    rows = rows.join(runs, "v").withColumn("b", F.col("lo") + F.pmod(F.col("h"), F.col("hi") - F.col("lo") + 1))
    return rows.groupBy("v", "lo", "hi").agg(F.count("*").alias("n"), F.min(F.col("b").between(F.col("lo"), F.col("hi"))).alias("inside"))


# Plans and costs ------------------------------------------------------------------------


@q(_beside_rows("SELECT CAST(n AS INT) AS n, CAST(c AS INT) AS cubes, c * power(b, 3) * 4 / 1048576 AS worker_mib, c * power(b, 3) * 4 / 1048576 * 2048 AS merge_mib, c * power(b, 3) * 4 / 1048576 <= 64 AS fits FROM (SELECT n, n * (n - 1) * (n - 2) / 6 AS c, 128 AS b FROM (SELECT unnest([4, 5, 8, 16, 24, 32]) AS n))"))
def q22b_plan_replicate(spark, sf):
    """What it would cost each of 2,048 units of 64 MiB to hold all cubes: from eight dimensions on they do not fit."""
    rows = []
    for n in (4, 5, 8, 16, 24, 32):
        p = T.plan_replicate(n, 2048, 128)
        rows.append((n, p["cubes"], p["worker_mib"], p["merge_mib"], p["worker_mib"] <= 64))
    return with_rows(spark, sf, spark.createDataFrame(rows, "n int, cubes int, worker_mib double, merge_mib double, fits boolean"))


_UNITS = [(n, u) for n in (16, 24) for u in (256, 512, 1000, 1024, 2048, 3000, 4096)]


def _unit_sql(n: int, u: int) -> str:
    r = u // 128
    return f"SELECT {n} AS n, {u} AS units, {r} AS owners, CAST(count(DISTINCT round) AS INT) AS rounds, CAST(count(DISTINCT owner) AS INT) AS copies, CAST((SELECT max(k) FROM (SELECT count(*) AS k FROM plan GROUP BY round, owner)) AS INT) AS most FROM plan"


@q(_beside_rows(" UNION ALL ".join(f"SELECT * FROM (WITH {plan_sql(n, u // 128)} {_unit_sql(n, u)})" for n, u in _UNITS)))
def q22c_plan_units(spark, sf):
    """Number of units, rounded down to a multiple of the bins: owners, rounds, copies of a row, triples of the fullest unit."""
    rows = []
    for n, u in _UNITS:
        p = T.unit_sweep(n, 128, u)
        rows.append((n, u, p["owners"], p["rounds"], p["copies"], round(p["unit_mib"] / (128 * 128 * 4 / 2**20))))
    return with_rows(spark, sf, spark.createDataFrame(rows, "n int, units int, owners int, rounds int, copies int, most int"))


@q(
    _beside_rows(
        "WITH t AS (SELECT a.i AS a, b.i AS b, c.i AS c FROM (SELECT unnest(range(9)) AS i) a, (SELECT unnest(range(9)) AS i) b, (SELECT unnest(range(9)) AS i) c WHERE a.i < b.i AND b.i < c.i), "
        "r AS (SELECT a, b, c, list_sort([(a + k) % 9, (b + k) % 9, (c + k) % 9]) AS s FROM t, (SELECT unnest(range(9)) AS k)), m AS (SELECT a, b, c, min(s) AS s FROM r GROUP BY ALL) "
        "SELECT CAST(s[1] AS INT) AS a, CAST(s[2] AS INT) AS b, CAST(s[3] AS INT) AS c, CAST(count(*) AS INT) AS size FROM m GROUP BY s"
    )
)
def q23b_orbits(spark, sf):
    """Triples of nine dimensions that rotations turn into each other."""
    return with_rows(spark, sf, spark.createDataFrame([(*t, size) for t, size in T.orbits(9)], "a int, b int, c int, size int"))


@q(
    _beside_rows(
        "SELECT CAST(n AS INT) AS n, CAST(b AS INT) AS bins, CAST(c * b * b * b AS BIGINT) AS cells, CAST(c * b * b * b * 4 AS BIGINT) AS bytes, CAST(c AS INT) AS updates, CAST(n AS INT) AS sent "
        "FROM (SELECT n, b, n * (n - 1) * (n - 2) // 6 AS c FROM (SELECT unnest([8, 16, 24, 32]) AS n), (SELECT unnest([32, 64, 128, 256]::BIGINT[]) AS b))"
    )
)
def q24b_costs(spark, sf):
    """Cells and bytes of all cubes, updates and copies of a row, by dimensions and bins."""
    rows = [(n, b, *cost.footprint(n, b, 4), cost.row_copies("local_dense", n), cost.row_copies("owner_slice", n)) for n in (8, 16, 24, 32) for b in (32, 64, 128, 256)]
    return with_rows(spark, sf, spark.createDataFrame(rows, "n int, bins int, cells long, bytes long, updates int, sent int"))


@q(_beside_rows("SELECT CAST(n AS INT) AS n, CAST(max(b) AS INT) AS bins FROM (SELECT n, b, n * (n - 1) * (n - 2) // 6 * b * b * b * 4 AS size FROM (SELECT unnest([8, 16, 24, 32]) AS n), (SELECT unnest([16, 32, 64, 128, 256]::BIGINT[]) AS b)) WHERE size <= 160::BIGINT * 1073741824 GROUP BY n"))
def q24c_suggest_bins(spark, sf):
    """The finest resolution whose cubes fit 160 GiB of four-byte cells."""
    return with_rows(spark, sf, spark.createDataFrame([(n, cost.suggest_bins(n, 160 << 30, 4)) for n in (8, 16, 24, 32)], "n int, bins int"))


# All triples at the sizes of the experiments --------------------------------------------


def _sizes_sql(specs, bins: int, log: bool = False, measures: str = "", sums: str = "") -> str:
    """One row a triple, in one pass: every row is unfolded to the cells of all triples."""
    n, b = len(specs), bins
    codes = ", ".join(f"{specs[i].bin} * {b * b} + {specs[j].bin} * {b} + {specs[k].bin}" for i, j, k in combinations(range(n), 3))
    triples = n * (n - 1) * (n - 2) // 6
    names = [m.rsplit(" AS ", 1)[1] for m in sums.split(" | ")] if sums else []
    carried = "".join(f", {x}" for x in names)
    sources = "".join(f", {m}" for m in measures.split(" | ")) if measures else ""
    inner = "".join(f", sum({x}) AS {x}" for x in names)
    return (
        f"WITH {Q.binned_sql(specs, bins, log)}, u AS (SELECT unnest(range({triples})) AS triple, unnest([{codes}]) AS code{sources} FROM binned), "
        f"cells AS (SELECT triple, code, count(*) AS cnt{inner} FROM u GROUP BY triple, code) "
        f"SELECT CAST(triple AS INT) AS triple, count(*) AS cells, CAST(sum(cnt) AS BIGINT) AS cnt, max(cnt) AS top, CAST(sum(cnt * (cnt + code // {b * b} + 3 * ((code // {b}) % {b}) + 7 * (code % {b}))) AS BIGINT) AS squares"
        + "".join(f", {s}" for s in (sums.split(" | ") if sums else []))
        + " FROM cells GROUP BY triple"
    )


def _sized(name, specs, bins, strategy, log=False, measures=(), sql=("", ""), **options):
    def run(spark, sf):
        rows = Q.binned(spark, sf, specs, bins, log) if measures else Q.bins_only(spark, sf, specs, bins, log)
        out = cube.summarise(cube.build_cube(rows, specs, bins, list(measures), strategy, **options), measures)
        return out.withColumns({m.name: F.round(m.name, 2) for m in measures if not m.integer}) if measures else out

    queries[name] = run
    oracles[name] = _sizes_sql(specs, bins, log, *sql)


_sized("q43_star16_owner_slice", C.STAR_DIMS[:16], 16, "owner_slice")
_sized("q43b_star16_local_dense", C.STAR_DIMS[:16], 16, "local_dense")
_sized("q43c_star24_owner_rounds", C.STAR_DIMS[:24], 8, "owner_slice", owners=12)
_sized("q43d_star32_owner_slice", C.STAR_DIMS, 8, "owner_slice")
_sized("q43e_star8_bins64", C.STAR_DIMS[:8], 64, "local_dense")
_sized("q43f_star8_bins128", C.STAR_DIMS[:8], 128, "owner_slice")
_sized("q44_log8_count", C.LOG_DIMS[:8], 16, "owner_slice", log=True)
_sized("q44b_log16_count", C.LOG_DIMS[:16], 16, "owner_slice", log=True)
_sized("q44c_log24_count", C.LOG_DIMS, 16, "local_dense", log=True)
_LOG_CENTS = C.MeasureSpec("cents", "value_cents")
_LOG_FLOAT = C.MeasureSpec("as_float", "CAST(CAST(value AS FLOAT) AS DOUBLE)", False)
_LOG_DOUBLE = C.MeasureSpec("as_double", "value", False)
_TYPES = ("value_cents AS cents | CAST(CAST(value AS FLOAT) AS DOUBLE) AS as_float | value AS as_double", "CAST(sum(cents) AS BIGINT) AS cents | round(sum(as_float), 2) AS as_float | round(sum(as_double), 2) AS as_double")
_sized("q44d_log16_types", C.LOG_DIMS[:16], 16, "local_dense", log=True, measures=(_LOG_CENTS, _LOG_FLOAT, _LOG_DOUBLE), sql=_TYPES)
_sized("q45_star16_parts2", C.STAR_DIMS[:16], 8, "per_triple", parts=2)

_COORDS = [DimensionSpec(f"e{i}", (f"e{i}",)) for i in range(32)]


def _coordinates(spark, sf):
    def make():
        d = C.table(spark, sf, "embeddings").select("vec_id", *[F.get("embedding", F.lit(i)).alias(f"e{i}") for i in range(32)])
        r = build_ranks(d, _COORDS, ("vec_id",))
        return materialize(binning.bin_by_rank(r, _COORDS, r.count(), 8), "coordinates")

    return Q.once(spark, ("coordinates", sf), make)


_COORD_TIES = {s.name: f"md5(concat_ws(':', '{s.name}', CAST(vec_id AS VARCHAR))), vec_id" for s in _COORDS}


@q(
    "WITH f AS (SELECT vec_id, " + ", ".join(f"embedding[{i + 1}] AS e{i}" for i in range(32)) + " FROM embeddings), binned AS (SELECT vec_id, "
    + ", ".join(f"CAST((row_number() OVER (ORDER BY {s.name}, {_COORD_TIES[s.name]}) - 1) // ((count(*) OVER () + 7) // 8) AS INT) AS {s.bin}" for s in _COORDS)
    + " FROM f)" + _sizes_sql(_COORDS, 8).split(", u AS", 1)[1].join([", u AS", ""])
)
def q46_coordinates32(spark, sf):
    """All 4,960 triples of 32 elements of an array column."""
    return cube.summarise(cube.build_cube(_coordinates(spark, sf), _COORDS, 8, [], "local_dense"))


# The recommender at its full size -------------------------------------------------------


def scored_sql(specs, bins: int, parts: int = 4) -> str:
    """... , scored AS (xdim, ydim, zdim, slab, score) of all slab images, by unfolding every row to all images."""
    n, image, names = len(specs), 0, []
    codes = []
    for t in combinations(range(n), 3):
        for z in range(3):
            x, y = (k for k in range(3) if k != z)
            names.append(f"({image}, '{specs[t[x]].name}', '{specs[t[y]].name}', '{specs[t[z]].name}')")
            codes.append(f"(({specs[t[z]].bin} * {parts}) // {bins}) * {bins * bins} + {specs[t[x]].bin} * {bins} + {specs[t[y]].bin}")
            image += 1
    return (
        f"{Q.binned_sql(specs, bins)}, u AS (SELECT unnest(range({image})) AS image, unnest([{', '.join(codes)}]) AS code FROM binned), c AS (SELECT image, code // {bins * bins} AS slab, code, count(*) AS v FROM u GROUP BY image, code), "
        f"tot AS (SELECT image, slab, sum(v) / {float(bins * bins)}::DOUBLE AS s FROM c GROUP BY ALL), names(image, xdim, ydim, zdim) AS (VALUES {', '.join(names)}), "
        f"scored AS (SELECT xdim, ydim, zdim, CAST(slab AS INT) AS slab, sum(CASE WHEN v > s THEN least(1.0::DOUBLE, v / s - 1) ELSE 0 END) / {float(bins * bins)} AS score FROM c JOIN tot USING (image, slab) JOIN names USING (image) GROUP BY ALL)"
    )


_SIXTEEN = C.STAR_DIMS[:16]


def scored16(spark, sf):
    """Scores of the 6,720 images of 16 dimensions at 16 bins, kept for the queries that rank them."""

    def make():
        c = materialize(cube.build_cube(Q.bins_only(spark, sf, _SIXTEEN, 16), _SIXTEEN, 16, [], "local_dense"), "cube")
        return materialize(recommend.score_cube(c, _SIXTEEN, 16, 4), "scored")

    return Q.once(spark, ("scored16", sf), make)


@q(f"WITH {scored_sql(_SIXTEEN, 16)}{groups_sql()} SELECT xdim, ydim, round(score, 9) AS score, images, group_rank FROM ordered")
def q78_recommender(spark, sf):
    """Sixteen dimensions at 16 bins in four slabs: 12 images for each of 560 triples, 120 groups in order."""
    g = recommend.score_groups(scored16(spark, sf))
    return g.select("xdim", "ydim", F.round("score", 9).alias("score"), "images", "group_rank")


def _ranked_sql(m: int, n: int, order: str = "DESC") -> str:
    return f"{groups_sql(order)}, inside AS (SELECT group_rank, CAST(row_number() OVER (PARTITION BY s.xdim, s.ydim ORDER BY round(s.score, 9) DESC, zdim, slab) AS INT) AS image_rank, s.xdim, s.ydim, zdim, slab, round(s.score, 9) AS score FROM scored s JOIN ordered o ON s.xdim = o.xdim AND s.ydim = o.ydim WHERE group_rank <= {m}) SELECT * FROM inside WHERE image_rank <= {n}"


@q(f"WITH {scored_sql(_SIXTEEN, 16)}{_ranked_sql(30, 1)}")
def q78b_top_groups(spark, sf):
    """The best image of each of the 30 groups that come first."""
    return recommend.recommend(scored16(spark, sf), 30, 1).withColumn("score", F.round("score", 9))


@q(f"WITH {scored_sql(_SIXTEEN, 16)}{_ranked_sql(10, 1, 'ASC')}")
def q60_bottom_groups(spark, sf):
    """The best image of each of the 10 groups of 120 that come last."""
    return recommend.recommend(scored16(spark, sf), 10, 1, ascending=True).withColumn("score", F.round("score", 9))


_PLANTED = [("price", "net_revenue"), ("price", "unit_price"), ("quantity", "unit_price")]


@q(f"WITH {scored_sql(_SIXTEEN, 16)}{groups_sql()} SELECT 10 AS m, sum(CASE WHEN group_rank <= 10 AND (xdim, ydim) IN ({', '.join(map(str, _PLANTED))}) THEN 1 ELSE 0 END) / {len(_PLANTED)}::DOUBLE AS recall FROM ordered")
def q78c_planted_recall(spark, sf):
    """Share of the axis pairs known to depend on each other among the first ten of 120 groups."""
    found = metrics.recall_at(recommend.score_groups(scored16(spark, sf)), _PLANTED, 10)
    return spark.createDataFrame([(10, float(found))], "m int, recall double")


# Evenness of bins of small subsets ------------------------------------------------------

_TOTAL, _FINE, _BINS = 1 << 22, 20, 128
_PARTS = (4, 64, 1024, 8192, 16384)
_RANDOM = "CAST(conv(substr(md5(CAST(id AS STRING)), 1, 8), 16, 10) AS BIGINT)"


def _subset_sql(kind: str, part: int) -> str:
    where = f"id < {_TOTAL // part}" if kind == "contiguous" else f"CAST('0x' || substr(md5(CAST(id AS VARCHAR)), 1, 8) AS BIGINT) < {(1 << 32) // part}"
    return (
        f"SELECT '{kind}' AS kind, {part} AS part, count(*) AS bins_used, CASE WHEN count(*) < {_BINS} THEN 0 ELSE min(n) END AS least, max(n) AS most FROM (SELECT bin, CAST(sum(cnt) AS BIGINT) AS n FROM "
        f"(SELECT bucket, cnt, (coalesce(sum(cnt) OVER (ORDER BY bucket ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) // ((sum(cnt) OVER () + {_BINS - 1}) // {_BINS})) AS bin FROM "
        f"(SELECT id >> 2 AS bucket, count(*) AS cnt FROM ids WHERE {where} GROUP BY 1)) GROUP BY bin)"
    )


@q(f"WITH ids AS (SELECT unnest(range({_TOTAL})) AS id) " + " UNION ALL ".join(f"SELECT * FROM ({_subset_sql(kind, part)})" for kind in ("contiguous", "random") for part in _PARTS))
def q79b_subset_sensitivity(spark, sf):
    """Evenness of 128 bins over 2**22 ranks and 2**20 fine buckets, of contiguous and random subsets: contiguous ones break first, below 1/2**13."""
    spec, out = DimensionSpec("v", ("v",)), None
    ids = spark.range(_TOTAL).select(F.col("id").alias("rk_v"), F.expr(_RANDOM).alias("h"))
    for kind in ("contiguous", "random"):
        for part in _PARTS:
            sub = ids.filter(F.col("rk_v") < _TOTAL // part) if kind == "contiguous" else ids.filter(F.col("h") < (1 << 32) // part)
            binned = binning.bin_by_histogram(sub, [spec], _TOTAL, _BINS, _FINE)
            one = binning.bin_balance(binned, [spec], _BINS).select(F.lit(kind).alias("kind"), F.lit(part).alias("part"), "bins_used", "least", "most")
            out = one if out is None else out.unionByName(one)
    return out


@q(f"WITH {Q.cube_sql(Q.DIMS, Q.BINS)} SELECT * FROM cube WHERE triple IN (3, 11, 19)")
def q47_cube_kept(spark, sf):
    """A cube is written by ranges of triples; three of them are read back."""
    c = cube.build_cube(Q.binned(spark, sf, Q.DIMS, Q.BINS), Q.DIMS, Q.BINS, [], "owner_slice")
    path = scratch(spark, "kept")
    cube.write_cube(c, path)
    return cube.read_cube(spark, path, [3, 11, 19])


@q(f"WITH {Q.cube_sql(Q.DIMS, Q.BINS)} SELECT * FROM cube")
def q47b_cube_synchronous(spark, sf):
    """Three rounds, all routed rows written before any unit starts."""
    return cube.build_cube(Q.binned(spark, sf, Q.DIMS, Q.BINS), Q.DIMS, Q.BINS, [], "owner_slice", owners=2, staged=True)


# Timings: measures without a twin -------------------------------------------------------


@q()
def q48_stage_times(spark, sf):
    """Seconds of filling, updating and reading back, their sum, and of the pipelined run (rounds of three owners)."""
    rows = cube.narrow(Q.binned(spark, sf, Q.DIMS, Q.BINS), Q.DIMS)
    times = metrics.staged_times(rows, Q.DIMS, Q.BINS, owners=3)
    return spark.createDataFrame(list(times.items()), "part string, seconds double")


@q()
def q48b_units_speedup(spark, sf):
    """Seconds of all triples by the number of tasks that work at a time, and the speed-up over one."""
    rows = Q.bins_only(spark, sf, Q.DIMS, Q.BINS)
    times = metrics.units_times(lambda d, k: cube.owner_slices(cube.narrow(d, Q.DIMS), Q.DIMS, Q.BINS, partitions=k), rows, [1, 2, 4])
    return spark.createDataFrame([(k, v, metrics.speedup(v, times[1])) for k, v in times.items()], "units int, seconds double, saved_percent double")


@q()
def q48c_insert_share(spark, sf):
    """What binning a hundredth of new rows by remembered bounds costs against ranking and binning all again."""
    e = C.table(spark, sf, "events")
    old = build_ranks(e.filter("NOT (event_id % 100 = 7)"), [L["ts"]], C.LOG_KEY)
    times = metrics.insert_share(old, e.filter("event_id % 100 = 7"), L["ts"], 16, C.LOG_KEY, old.count(), 8)
    return spark.createDataFrame([(k, float(v)) for k, v in times.items()], "part string, seconds double")


# Images ---------------------------------------------------------------------------------

_SIGNED = [L[k] for k in ("value", "gap_prev", "minute_of_day", "nth")]
_DELTA = C.MeasureSpec("delta", "CAST(round(value_delta * 100) AS BIGINT)")
_DELTA_SQL = ", CAST(coalesce(sum(CAST(round(value_delta * 100) AS BIGINT)), 0) AS BIGINT) AS delta"
KEYS = "xdim, ydim, zdim, slab"


@q(
    f"WITH {Q.images_sql(_SIGNED, 8, 4, True, _DELTA_SQL, 'delta')}, t AS (SELECT {KEYS}, sum(v) / 64.0::DOUBLE AS expected FROM cells GROUP BY ALL) SELECT {KEYS}, x, y, v, expected <= 0 AS degenerate, "
    "round(CASE WHEN expected > 0 AND v > expected THEN least(1.0::DOUBLE, v / expected - 1) ELSE 0 END, 7) AS r, round(CASE WHEN expected > 0 AND v <= expected THEN least(1.0::DOUBLE, 1 - v / expected) ELSE 0 END, 7) AS b FROM cells JOIN t USING (xdim, ydim, zdim, slab)"
)
def q51b_signed_sums(spark, sf):
    """Sums of changes may add up to nothing or less: such images are black and marked."""
    c = cube.build_cube(Q.binned(spark, sf, _SIGNED, 8, log=True), _SIGNED, 8, [_DELTA], "owner_slice").withColumn("delta", F.coalesce("delta", F.lit(0)))
    out = I.diverging(image.slab_images(c, _SIGNED, 8, 4, "delta"), 8)
    return out.select("xdim", "ydim", "zdim", "slab", "x", "y", "v", "degenerate", F.round("r", 7).alias("r"), F.round("b", 7).alias("b"))


_THIRDS = Q.images_sql(Q.DIMS, Q.BINS, 3)


def _scope(name, scope, share):
    """Three slabs of eight bins are three, three and two bins wide."""

    def run(spark, sf):
        c = cube.build_cube(Q.binned(spark, sf, Q.DIMS, Q.BINS), Q.DIMS, Q.BINS, [], "local_dense")
        out = recommend.score_images(image.slab_images(c, Q.DIMS, Q.BINS, 3), Q.BINS, scope, z_parts=3)
        return out.select("xdim", "ydim", "zdim", "slab", F.round("expected", 9).alias("expected"), F.round("score", 9).alias("score"))

    queries[name] = run
    keys = KEYS if scope == "slab" else "xdim, ydim, zdim"
    oracles[name] = (
        f"WITH {_THIRDS}, t AS (SELECT {keys}, sum(v) / 64.0::DOUBLE AS s FROM cells GROUP BY ALL), e AS (SELECT cells.*, s * {share} AS expected FROM cells JOIN t USING ({keys})) "
        f"SELECT {KEYS}, round(any_value(expected), 9) AS expected, round(sum(CASE WHEN v > expected THEN least(1.0::DOUBLE, v / expected - 1) ELSE 0 END) / 64.0, 9) AS score FROM e GROUP BY {KEYS}"
    )


_scope("q51c_scope_slab", "slab", "1")
_scope("q51d_scope_dataset", "dataset", "1")
_scope("q51e_scope_dataset_share", "dataset_share", "(CASE slab WHEN 2 THEN 2 ELSE 3 END / 8.0::DOUBLE)")


@q(
    f"WITH {Q.images_sql(Q.DIMS, Q.BINS, 4)}, t AS (SELECT {KEYS}, sum(v) / 64.0::DOUBLE AS s FROM cells GROUP BY ALL) "
    f"SELECT {KEYS}, x, y, v, round(least(1, v / (2 * s)), 9) AS r, round(1 - abs(1 - least(2, v / s)), 9) AS g, round(1 - least(1, v / (2 * s)), 9) AS b FROM cells JOIN t USING ({KEYS})"
)
def q51f_any_intensity(spark, sf):
    """An analyst's own colours: from blue over green at the expected value to red at twice it."""

    def own(v, s):
        half = F.least(F.lit(1.0), v / (2 * s))
        return half, 1 - F.abs(1 - F.least(F.lit(2.0), v / s)), 1 - half

    out = I.colour(M.cells(spark, sf), Q.BINS, own)
    return out.select("xdim", "ydim", "zdim", "slab", "x", "y", "v", *[F.round(c, 9).alias(c) for c in "rgb"])


_FLOOR = "0.3989 / sqrt(expected + 1.283 * exp(-0.518 * (expected - 1)))"


@q(f"WITH {Q.images_sql(Q.DIMS, Q.BINS, 4)}{Q.scores_sql(Q.BINS)} SELECT {KEYS}, round(score - {_FLOOR}, 7) AS excess FROM scored")
def q56b_score_minus_noise(spark, sf):
    """Scores less what independent rows would show at the same density."""
    return recommend.score_minus_noise(M.scored(spark, sf)).select("xdim", "ydim", "zdim", "slab", F.round("excess", 7).alias("excess"))


@q(f"WITH {Q.images_sql(Q.DIMS, Q.BINS, 4)}{Q.scores_sql(Q.BINS)} SELECT {KEYS}, CAST(total AS BIGINT) AS total, expected, round(score, 9) AS score FROM scored")
def q56c_score_cube(spark, sf):
    """Scores of all images straight from the cube's cells, no picture table in between."""
    c = cube.build_cube(Q.binned(spark, sf, Q.DIMS, Q.BINS), Q.DIMS, Q.BINS, [], "local_dense")
    return recommend.score_cube(c, Q.DIMS, Q.BINS, 4).select("xdim", "ydim", "zdim", "slab", "total", "expected", F.round("score", 9).alias("score"))


@q(f"WITH {Q.images_sql(Q.DIMS, Q.BINS, 4)}{Q.scores_sql(Q.BINS)}{groups_sql()} SELECT xdim, ydim, zdim, CAST(count(DISTINCT slab) * {Q.BINS} + (count(DISTINCT slab) - 1) * 2 AS INT) AS width, {Q.BINS} AS height, true AS is_png FROM scored JOIN ordered USING (xdim, ydim) WHERE group_rank <= 2 GROUP BY xdim, ydim, zdim")
def q61b_montage(spark, sf):
    """The slabs of the two best groups side by side, one picture for each third dimension."""
    best = recommend.score_groups(M.scored(spark, sf)).filter("group_rank <= 2").select("xdim", "ydim")
    wanted = M.cells(spark, sf).join(F.broadcast(best), ["xdim", "ydim"], "left_semi")
    out = render.montage(I.diverging(wanted, Q.BINS), Q.BINS)
    return out.select("xdim", "ydim", "zdim", "width", "height", (F.substring(F.hex("png"), 1, 16) == "89504E470D0A1A0A").alias("is_png"))


@q(
    f"WITH {Q.binned_sql([S['quantity'], S['priority']], 16)} SELECT 'quantity' AS dim, b_quantity AS bin, CAST(CAST(min(l_quantity) AS INT) AS VARCHAR) AS lo, CAST(CAST(max(l_quantity) AS INT) AS VARCHAR) AS hi, count(*) AS n FROM binned WHERE b_quantity = 3 GROUP BY 2"
    " UNION ALL SELECT 'priority', b_priority, min(o_orderpriority), max(o_orderpriority), count(*) FROM binned WHERE b_priority = 9 GROUP BY 2"
)
def q62b_hover(spark, sf):
    """The value ranges behind one cell of a picture."""
    specs = [S["quantity"], S["priority"]]
    out = image.hover(binning.axis_table(Q.binned(spark, sf, specs, 16), specs), "quantity", "priority", 3, 9)
    whole = lambda c: F.regexp_replace(c, r"\.0$", "").alias(c)
    return out.select("dim", "bin", whole("lo"), whole("hi"), "n")


# Measures behind the pictures -----------------------------------------------------------


@q(f"WITH {Q.binned_sql([S['discount']], 128)} SELECT CAST(l_discount + 0.0 AS VARCHAR) AS value, count(DISTINCT b_discount) AS bins, count(*) AS rows, count(DISTINCT b_discount) / 128.0::DOUBLE AS share FROM binned GROUP BY 1")
def q72b_axis_share(spark, sf):
    """How many of 128 bins each value of a heavy-valued dimension owns."""
    spec = S["discount"]
    out = metrics.axis_share(Q.binned(spark, sf, [spec], 128), spec.bin, spec.keys[0])
    return out.withColumn("share", F.col("bins") / 128)


def _area(name, specs, bins, log=False):
    x, y = specs

    def run(spark, sf):
        pairs = cube.build_pairs(Q.binned(spark, sf, specs, bins, log), specs, bins=bins)
        return metrics.area_by_color(I.diverging(image.pair_images(pairs, specs), bins), bins)

    queries[name] = run
    oracles[name] = (
        f"WITH {Q.binned_sql(specs, bins, log)}, c AS (SELECT {x.bin} AS x, {y.bin} AS y, count(*) AS v FROM binned GROUP BY 1, 2), s AS (SELECT sum(v) / {float(bins * bins)}::DOUBLE AS s FROM c) "
        f"SELECT '{x.name}' AS xdim, '{y.name}' AS ydim, '' AS zdim, 0 AS slab, sum(CASE WHEN v > s AND least(1, v / s - 1) >= 0.5 THEN 1 ELSE 0 END) / {float(bins * bins)}::DOUBLE AS red_area, "
        f"(sum(CASE WHEN v <= s AND 1 - v / s >= 0.5 THEN 1 ELSE 0 END) + {bins * bins} - count(*)) / {float(bins * bins)}::DOUBLE AS blue_area FROM c, s"
    )


_area("q72c_area_equal_population", [S["price"], S["discount"]], 16)
_area("q72d_area_secondary", [S["price"], S["discount_by_time"]], 16)
_area("q72e_area_planted", [S["price"], S["net_revenue"]], 16)


_FLAT = "SELECT least(CAST(floor(l_extendedprice) AS BIGINT) * 16 // (SELECT CAST(floor(max(l_extendedprice)) AS BIGINT) + 1 FROM lineitem) {0}, 15) AS x, least(CAST(l_quantity AS BIGINT) * 16 // 51, 15) AS y, count(*) AS v FROM lineitem GROUP BY 1, 2"


@q(
    " UNION ALL ".join(
        f"SELECT {part} AS outlier_factor, sum(CASE WHEN v > s AND least(1, v / s - 1) >= 0.5 THEN 1 ELSE 0 END) / 256.0::DOUBLE AS red_area, (sum(CASE WHEN v <= s AND 1 - v / s >= 0.5 THEN 1 ELSE 0 END) + 256 - count(*)) / 256.0::DOUBLE AS blue_area FROM ({_FLAT.format(f'// {part}')}), (SELECT count(*) / 256.0::DOUBLE AS s FROM lineitem)"
        for part in (1, 1000)
    )
)
def q72f_area_equal_width(spark, sf):
    """Equal-width picture of price and quantity with and without one far outlier on the price axis: how much of it is used."""
    d = C.table(spark, sf, "lineitem")
    top = d.agg(F.floor(F.max("l_extendedprice"))).first()[0] + 1
    out = None
    for part in (1, 1000):
        x = F.least(F.expr(f"CAST(floor(l_extendedprice) AS BIGINT) * 16 div {top} div {part}"), F.lit(15)).cast("int")
        y = F.least(F.expr("CAST(l_quantity AS BIGINT) * 16 div 51"), F.lit(15)).cast("int")
        cells = d.groupBy(x.alias("x"), y.alias("y")).agg(F.count("*").alias("v"))
        cells = cells.select(F.lit("price").alias("xdim"), F.lit("quantity").alias("ydim"), F.lit("").alias("zdim"), F.lit(0).alias("slab"), "x", "y", "v")
        one = metrics.area_by_color(I.diverging(cells, 16), 16).select(F.lit(part).alias("outlier_factor"), "red_area", "blue_area")
        out = one if out is None else out.unionByName(one)
    return out
