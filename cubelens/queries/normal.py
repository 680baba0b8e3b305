"""Queries q01 - q20: ranks, bins, their baselines and inserts."""

from __future__ import annotations

from pyspark.sql import functions as F

from cubelens.dimension import tie_sql
from cubelens.operators import baselines, binning, insert
from cubelens.operators.rank import build_ranks
from cubelens.queries import base as Q
from cubelens.sources import catalog as C

KEY = ", ".join(C.STAR_KEY)
S = C.STAR
THREE = [S["price"], S["quantity"], S["ship_time"]]
queries, oracles = {}, {}


def register(name, sql=None):
    def keep(fn):
        queries[name] = fn
        if sql:
            oracles[name] = sql
        return fn

    return keep


def _rank(name, spec):
    @register(name, f"WITH {Q.ranked_sql([spec])} SELECT {KEY}, {spec.rank} FROM ranked")
    def run(spark, sf, spec=spec):
        d, _ = Q.ranked(spark, sf, [spec])
        return d.select(*Q.key_columns(), spec.rank)


_rank("q01_rank_quantity", S["quantity"])
_rank("q02_rank_composite", S["discount_by_time"])


def _bins(name, specs, bins, log=False, rule="ceil"):
    key = ", ".join(C.LOG_KEY if log else C.STAR_KEY)

    @register(name, f"WITH {Q.binned_sql(specs, bins, log, rule)} SELECT {key}, {', '.join(s.bin for s in specs)} FROM binned")
    def run(spark, sf):
        d = Q.binned(spark, sf, specs, bins, log, rule)
        return d.select(*Q.key_columns(log), *[F.col(s.bin).cast("int").alias(s.bin) for s in specs])


_bins("q03_bin_exact_ceil", THREE, 16)
_bins("q04_bin_exact_proportional", THREE, 16, rule="proportional")
_bins("q09_bin_nulls_first", [C.LOG["gap_prev"], C.LOG["value_delta"]], 16, log=True)
_bins("q10_bin_secondary", [S["discount"], S["discount_by_time"], S["flag_by_time"]], 16)

FINE, PAIR = 8, [S["price"], S["discount"]]


def _hist_sql(fine, bins, where=""):
    shift = f"greatest(0, CAST(ceil(log2(n)) AS INT) - {fine})"
    hist = " UNION ALL ".join(f"SELECT '{s.name}' AS dim, CAST({s.rank} >> {shift} AS INT) AS bucket, count(*) AS cnt FROM ranked {where} GROUP BY ALL" for s in PAIR)
    return (
        f"WITH {Q.ranked_sql(PAIR)}, hist AS ({hist}), m AS (SELECT count(*) AS m FROM ranked {where}), "
        "pos AS (SELECT dim, bucket, cnt, CAST(coalesce(sum(cnt) OVER (PARTITION BY dim ORDER BY bucket ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS pos FROM hist), "
        f"placed AS (SELECT *, CAST(pos // ((m + {bins - 1}) // {bins}) AS INT) AS bin FROM pos, m)"
    )


@register("q05_fine_histogram", _hist_sql(FINE, 16) + " SELECT dim, bucket, cnt FROM hist")
def q05(spark, sf):
    d, n = Q.ranked(spark, sf, PAIR)
    return binning.fine_histogram(d, PAIR, n, FINE)


@register("q06_hist_cuts", _hist_sql(FINE, 16) + " SELECT dim, bin, min(bucket) AS first_bucket, min(pos) AS first_pos FROM placed GROUP BY dim, bin")
def q06(spark, sf):
    d, n = Q.ranked(spark, sf, PAIR)
    return binning.histogram_cuts(binning.fine_histogram(d, PAIR, n, FINE), n, 16)


def _looked_up(fine, bins, where=""):
    shift = f"greatest(0, CAST(ceil(log2(n)) AS INT) - {fine})"
    joins = " ".join(f"JOIN placed p{i} ON p{i}.dim = '{s.name}' AND p{i}.bucket = {s.rank} >> {shift}" for i, s in enumerate(PAIR))
    return _hist_sql(fine, bins, where) + f" SELECT {KEY}, {', '.join(f'p{i}.bin AS {s.bin}' for i, s in enumerate(PAIR))} FROM ranked {joins} {where}"


def _histogram(name, where, how, fine=FINE):
    @register(name, _looked_up(fine, 16, f"WHERE {where}" if where else ""))
    def run(spark, sf):
        d, n = Q.ranked(spark, sf, PAIR)
        d = d.filter(where) if where else d
        out = binning.bin_by_histogram(d, PAIR, n, 16, fine, how)
        return out.select(*Q.key_columns(), *[F.col(s.bin).cast("int").alias(s.bin) for s in PAIR])


_histogram("q07_bin_histogram", "", "steps")
_histogram("q08_bin_subset", "l_returnflag = 'R'", "search", 10)
_histogram("q08b_bin_subset_join", "l_quantity >= 49", "join")

_ORDERS = [S["cust_nation"], C.NATION_BY_NAME, C.NATION_BY_BALANCE]
_ORDERED = "SELECT f.*, nation_balance FROM ({0}) f JOIN (SELECT c_nationkey AS k, CAST(round(avg(CAST(round(c_acctbal * 100) AS BIGINT))) AS BIGINT) AS nation_balance FROM customer GROUP BY c_nationkey) ON c_nationkey = k"


@register(
    "q11_bin_category_orders",
    f"WITH facts AS ({_ORDERED.format(C.STAR_SQL)}), r AS (SELECT {KEY}, count(*) OVER () AS n, "
    + ", ".join(f"row_number() OVER (ORDER BY {s.order_sql()}, {tie_sql(s, C.STAR_KEY)}) - 1 AS {s.rank}" for s in _ORDERS)
    + f" FROM facts) SELECT {KEY}, "
    + ", ".join(f"CAST({s.rank} // ((n + 15) // 16) AS INT) AS {s.bin}" for s in _ORDERS)
    + " FROM r",
)
def q11(spark, sf):
    nations = C.table(spark, sf, "customer").groupBy(F.col("c_nationkey").alias("k")).agg(F.round(F.avg(F.round(F.col("c_acctbal") * 100).cast("long"))).cast("long").alias("nation_balance"))
    d = C.order_star(spark, sf).join(nations, F.col("c_nationkey") == F.col("k")).drop("k")
    r = build_ranks(d, _ORDERS, C.STAR_KEY)
    out = binning.bin_by_rank(r, _ORDERS, r.count(), 16)
    return out.select(*Q.key_columns(), *[F.col(s.bin).cast("int").alias(s.bin) for s in _ORDERS])


@register(
    "q12_equidepth_whole",
    f"WITH facts AS ({C.STAR_SQL}), v AS (SELECT l_quantity AS q, count(*) AS c FROM facts GROUP BY 1), "
    "p AS (SELECT q, c, coalesce(sum(c) OVER (ORDER BY q ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) // (((SELECT count(*) FROM facts) + 15) // 16) AS raw FROM v), "
    "g AS (SELECT raw, sum(c) AS rws, row_number() OVER (ORDER BY raw) - 1 AS b FROM p GROUP BY raw) "
    f"SELECT {KEY}, CAST(b AS INT) AS b_quantity, round(CAST(rws AS DOUBLE) / (SELECT count(*) FROM facts), 9) AS width FROM facts JOIN p ON l_quantity = q JOIN g USING (raw)",
)
def q12(spark, sf):
    out = baselines.bin_equidepth_whole(C.order_star(spark, sf), S["quantity"], 16)
    return out.select(*Q.key_columns(), F.col("b_quantity").cast("int").alias("b_quantity"), F.round("width", 9).alias("width"))


_WIDTH = "CAST(least(floor((v - lo) / (hi - lo) * {b}), {b} - 1) AS INT)"


@register("q13_equidistance", f"WITH e AS (SELECT min(cents) lo, max(cents) hi FROM (SELECT CAST(round(l_extendedprice * 100) AS BIGINT) AS cents FROM lineitem)), c AS (SELECT CAST(round(l_extendedprice * 100) AS BIGINT) AS v FROM lineitem) SELECT CAST(least((v - lo) * 32 // (hi - lo), 31) AS INT) AS b, count(*) AS n FROM c, e GROUP BY 1")
def q13(spark, sf):
    d = C.table(spark, sf, "lineitem").withColumn("cents", F.round(F.col("l_extendedprice") * 100).cast("long"))
    low, high = d.agg(F.min("cents"), F.max("cents")).first()
    exact = F.least(F.expr(f"((cents - {low}) * 32) div {high - low}"), F.lit(31)).cast("int")  # integer arithmetic: exact at the edges
    return d.groupBy(exact.alias("b")).agg(F.count("*").alias("n"))


@register("q14_equidistance_clipped", "SELECT CAST(least(floor((l_quantity - 0) / 40 * 16), 15) AS INT) AS b, count(*) AS n FROM lineitem WHERE l_quantity BETWEEN 0 AND 40 AND l_discount BETWEEN 0 AND 0.05 GROUP BY 1")
def q14(spark, sf):
    d = baselines.clip_rows(C.table(spark, sf, "lineitem"), {"l_quantity": (0, 40), "l_discount": (0, 0.05)})
    return baselines.bin_equidistance(d, "l_quantity", 16, 0, 40).groupBy("b").agg(F.count("*").alias("n"))


@register("q15_categorical", "WITH v AS (SELECT p_brand, row_number() OVER (ORDER BY p_brand) - 1 AS b FROM (SELECT DISTINCT p_brand FROM part)) SELECT p_partkey, CAST(b AS INT) AS b FROM part JOIN v USING (p_brand)")
def q15(spark, sf):
    return baselines.bin_categorical(C.table(spark, sf, "part"), "p_brand").select("p_partkey", "b")


@register("q16_packed_composite", "WITH c AS (SELECT year(o_orderdate) * 10000 + month(o_orderdate) * 100 + day(o_orderdate) AS v FROM orders), e AS (SELECT min(v) lo, max(v) hi FROM c) SELECT CAST(least(floor(CAST(v - lo AS DOUBLE) / (hi - lo) * 32), 31) AS INT) AS b, count(*) AS n FROM c, e GROUP BY 1")
def q16(spark, sf):
    d = C.table(spark, sf, "orders")
    return baselines.bin_packed(d, "year(o_orderdate) * 10000 + month(o_orderdate) * 100 + day(o_orderdate)", 32).groupBy("b").agg(F.count("*").alias("n"))


_AXIS = [S["quantity"], S["priority"]]


@register(
    "q17_axis_hover",
    f"WITH {Q.binned_sql(_AXIS, 16)} SELECT 'quantity' AS dim, b_quantity AS bin, CAST(CAST(min(l_quantity) AS INT) AS VARCHAR) AS lo, CAST(CAST(max(l_quantity) AS INT) AS VARCHAR) AS hi, count(*) AS n FROM binned GROUP BY 2"
    " UNION ALL SELECT 'priority', b_priority, min(o_orderpriority), max(o_orderpriority), count(*) FROM binned GROUP BY 2",
)
def q17(spark, sf):
    out = binning.axis_table(Q.binned(spark, sf, _AXIS, 16), _AXIS)
    whole = lambda c: F.regexp_replace(c, r"\.0$", "").alias(c)
    return out.select("dim", "bin", whole("lo"), whole("hi"), "n")


@register(
    "q18_bin_balance",
    f"WITH {Q.binned_sql(PAIR, 16)}, c AS (SELECT 'price' AS dim, b_price AS b, count(*) AS n FROM binned GROUP BY 2 UNION ALL SELECT 'discount', b_discount, count(*) FROM binned GROUP BY 2) "
    "SELECT dim, count(*) AS bins_used, CASE WHEN count(*) < 16 THEN 0 ELSE min(n) END AS least, max(n) AS most, round(CAST(sum(n) AS DOUBLE) / 16, 6) AS ideal, "
    "round(sqrt(greatest(CAST(sum(n * n) AS DOUBLE) / 16 - (sum(n) / 16.0::DOUBLE) ** 2, 0)) / (sum(n) / 16.0::DOUBLE), 6) AS cv FROM c GROUP BY dim",
)
def q18(spark, sf):
    return binning.bin_balance(Q.binned(spark, sf, PAIR, 16), PAIR, 16)


_ONE = ["c_custkey", "c_name", "c_nationkey", "n_name", "r_name", "n_regionkey"]


@register(
    "q19_one_to_one",
    "WITH t AS (SELECT * FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey) SELECT * FROM ("
    + " UNION ALL ".join(f"SELECT '{a}' AS a, '{b}' AS b WHERE (SELECT count(*) FROM (SELECT DISTINCT {a}, {b} FROM t)) = (SELECT count(DISTINCT {a}) FROM t) AND (SELECT count(*) FROM (SELECT DISTINCT {a}, {b} FROM t)) = (SELECT count(DISTINCT {b}) FROM t)" for i, a in enumerate(_ONE) for b in _ONE[i + 1 :])
    + ")",
)
def q19(spark, sf):
    t = lambda n: C.table(spark, sf, n)
    d = t("customer").join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    _, pairs = binning.drop_one_to_one(d, _ONE)
    return spark.createDataFrame(pairs, "a string, b string")


_NEW = "event_id % 100 = 7"


@register(
    "q20_insert_bins",
    f"WITH old AS (SELECT event_id, ts, row_number() OVER (ORDER BY ts, md5(concat_ws(':', 'ts', CAST(event_id AS VARCHAR))), event_id) - 1 AS rk FROM events WHERE NOT ({_NEW})), "
    "h AS (SELECT CAST(rk >> greatest(0, CAST(ceil(log2((SELECT count(*) FROM old))) AS INT) - 8) AS INT) AS bucket, count(*) AS cnt, arg_min(ts, rk) AS first_ts FROM old GROUP BY 1), "
    f"new AS (SELECT event_id, ts, coalesce((SELECT max(bucket) FROM h WHERE first_ts <= e.ts), 0) AS bucket FROM events e WHERE {_NEW}), "
    "a AS (SELECT bucket, CAST(sum(c) AS BIGINT) AS cnt FROM (SELECT bucket, cnt AS c FROM h UNION ALL SELECT bucket, count(*) FROM new GROUP BY 1) GROUP BY 1), "
    "p AS (SELECT bucket, coalesce(sum(cnt) OVER (ORDER BY bucket ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) // (((SELECT count(*) FROM events) + 15) // 16) AS bin FROM a) "
    "SELECT event_id, CAST(bin AS INT) AS b_ts FROM new JOIN p USING (bucket)",
)
def q20(spark, sf):
    events, spec = C.table(spark, sf, "events"), C.LOG["ts"]
    old = build_ranks(events.filter(f"NOT ({_NEW})"), [spec], C.LOG_KEY)
    bounds = insert.capture_bounds(old, spec, old.count(), 8)
    out, _ = insert.bin_inserts(events.filter(_NEW), bounds, spec, 16, C.LOG_KEY)
    return out.select("event_id", F.col("b_ts").cast("int").alias("b_ts"))
