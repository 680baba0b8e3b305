"""Queries q80 - q129: what surrounds the method, from scans to subqueries, one for each operator family."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from cubelens import sql as S
from cubelens.operators.rank import running
from cubelens.queries.plan import plan_sql
from cubelens.sources import catalog as C
from cubelens.sources import formats

queries, oracles = {}, {}


class T:
    """Tables of one scale factor by attribute."""

    def __init__(self, spark, sf):
        self._at = spark, sf

    def __getattr__(self, name):
        return C.table(*self._at, name)


def q(sql=None):
    def keep(fn):
        queries[fn.__name__] = lambda spark, sf: fn(T(spark, sf), spark)
        if sql:
            oracles[fn.__name__] = sql
        return fn

    return keep


cents = lambda c: F.round(F.col(c) * 100).cast("long")
CENTS = "CAST(round({} * 100) AS BIGINT)"


@q("SELECT l_orderkey AS order_key, l_linenumber, CAST(l_quantity AS BIGINT) * 2 AS twice, " + CENTS.format("l_extendedprice") + " AS cents FROM lineitem")
def q80_scan_project(t, s):
    return t.lineitem.select(F.col("l_orderkey").alias("order_key"), "l_linenumber", (F.col("l_quantity").cast("long") * 2).alias("twice"), cents("l_extendedprice").alias("cents"))


@q("SELECT p_partkey, p_brand FROM part WHERE (p_size BETWEEN 10 AND 20 AND p_brand IN ('Brand#11', 'Brand#23') OR p_type LIKE 'PROMO%') AND p_name IS NOT NULL")
def q81_filter_predicates(t, s):
    return t.part.filter((F.col("p_size").between(10, 20) & F.col("p_brand").isin("Brand#11", "Brand#23") | F.col("p_type").like("PROMO%")) & F.col("p_name").isNotNull()).select("p_partkey", "p_brand")


@q(f"SELECT count(*) AS n, CAST(sum(cents) AS BIGINT) AS cents FROM ({C.STAR_SQL})")
def q82_star_join(t, s):
    return C.order_star(s, t._at[1]).agg(F.count("*").alias("n"), F.sum("cents").alias("cents"))


_JOIN = "SELECT o_orderpriority, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS units FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"


def _joined(t, hint):
    d = t.lineitem.join(t.orders.hint(hint), F.col("l_orderkey") == F.col("o_orderkey"))
    return d.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("units"))


@q(_JOIN)
def q83_sort_merge_join(t, s):
    return _joined(t, "merge")


@q(_JOIN)
def q84_shuffle_hash_join(t, s):
    return _joined(t, "shuffle_hash")


@q("SELECT d.doc_id, quality, toxic FROM documents d LEFT JOIN labels USING (doc_id)")
def q85_left_join_nulls(t, s):
    return t.documents.select("doc_id").join(t.labels, "doc_id", "left")


@q("SELECT o_orderkey, l_orderkey FROM (SELECT o_orderkey FROM orders WHERE o_orderkey % 3 = 0) FULL JOIN (SELECT DISTINCT l_orderkey FROM lineitem WHERE l_orderkey % 5 = 0) ON o_orderkey = l_orderkey")
def q86_right_full_join(t, s):
    return t.orders.filter("o_orderkey % 3 = 0").select("o_orderkey").join(t.lineitem.filter("l_orderkey % 5 = 0").select("l_orderkey").distinct(), F.col("o_orderkey") == F.col("l_orderkey"), "outer")


@q("SELECT o_orderkey FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_returnflag = 'R')")
def q87_semi_join(t, s):
    return t.orders.join(t.lineitem.filter("l_returnflag = 'R'"), F.col("l_orderkey") == F.col("o_orderkey"), "left_semi").select("o_orderkey")


@q("SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def q88_anti_join(t, s):
    return t.orders.join(t.lineitem, F.col("l_orderkey") == F.col("o_orderkey"), "left_anti").select("o_orderkey")


@q("SELECT n_name, r_name FROM nation CROSS JOIN region")
def q89_cross_join(t, s):
    """The grid of two lookup tables of fixed size (25 and 5 rows at every scale)."""
    return t.nation.select("n_name").crossJoin(t.region.select("r_name"))


@q("SELECT s_suppkey, count(*) AS n FROM supplier JOIN customer ON s_nationkey = c_nationkey AND s_acctbal > c_acctbal GROUP BY 1")
def q90_theta_join(t, s):
    """How many partners satisfy an inequality is a running count in the order of (key, value): no pair is made."""
    one = t.supplier.select(F.col("s_nationkey").alias("k"), F.col("s_acctbal").alias("v"), "s_suppkey", F.lit(0).alias("c"))
    two = t.customer.select(F.col("c_nationkey").alias("k"), F.col("c_acctbal").alias("v"), F.lit(None).cast("long").alias("s_suppkey"), F.lit(1).alias("c"))
    placed = running(one.unionByName(two), [F.col("k"), F.col("v"), F.col("c"), F.col("s_suppkey")], "c")
    starts = placed.groupBy("k").agg(F.min("before_").alias("start"))
    return placed.filter("c = 0").join(starts, "k").select("s_suppkey", (F.col("before_") - F.col("start")).alias("n")).filter("n > 0")


@q("SELECT edge, count(*) AS n FROM lineitem JOIN (SELECT unnest(range(0, 50, 5)) AS edge) ON l_quantity >= edge AND l_quantity < edge + 5 GROUP BY 1")
def q91_range_join(t, s):
    """Range join through a grid: the edge below a value is an equi-join key."""
    edges = s.range(0, 50, 5).withColumnRenamed("id", "edge")
    return t.lineitem.withColumn("k", F.floor(F.col("l_quantity") / 5) * 5).join(F.broadcast(edges), F.col("k") == F.col("edge")).groupBy("edge").agg(F.count("*").alias("n"))


@q("WITH e AS (SELECT user_id, min(ts) AS ts FROM events GROUP BY user_id) SELECT user_id, max(o_orderdate) AS last_order FROM e LEFT JOIN orders ON o_custkey = user_id AND o_orderdate <= ts GROUP BY user_id")
def q92_asof_join(t, s):
    """Last order before each user's first event: union of both in time order, last known value carried on."""
    first = t.events.groupBy("user_id").agg(F.min("ts").alias("ts"))
    both = t.orders.select(F.col("o_custkey").alias("user_id"), F.col("o_orderdate").alias("ts"), F.lit(0).alias("side"), F.col("o_orderdate").alias("d")).unionByName(first.select("user_id", "ts", F.lit(1).alias("side"), F.lit(None).cast(dict(t.orders.dtypes)["o_orderdate"]).alias("d")))
    order = W.partitionBy("user_id").orderBy("ts", "side")
    return both.withColumn("last_order", F.last("d", ignorenulls=True).over(order)).filter("side = 1").select("user_id", "last_order")


@q("WITH i AS (SELECT o_custkey, o_orderkey, o_orderdate AS a, o_orderdate + INTERVAL 30 DAY AS z FROM orders) SELECT x.o_orderkey AS first_key, y.o_orderkey AS second_key FROM i x JOIN i y ON x.o_custkey = y.o_custkey AND x.o_orderkey < y.o_orderkey AND x.a <= y.z AND y.a <= x.z")
def q93_interval_join(t, s):
    """Intervals meet in the cells of a grid as wide as they are long; a pair counts in the cell in which its later one begins."""
    start = F.unix_micros(F.col("o_orderdate").cast("timestamp"))
    wide = 30 * 86_400_000_000
    i = t.orders.select("o_custkey", "o_orderkey", start.alias("a"), (start + wide).alias("z"), F.expr(f"unix_micros(CAST(o_orderdate AS TIMESTAMP)) div {wide}").alias("first"))
    i = i.withColumn("cell", F.explode(F.sequence(F.col("first"), F.expr(f"z div {wide}"))))
    x, y = i.alias("x"), i.alias("y")
    near = x.join(y, F.expr("x.o_custkey = y.o_custkey AND x.cell = y.cell AND x.o_orderkey < y.o_orderkey AND x.a <= y.z AND y.a <= x.z AND x.cell = greatest(x.first, y.first)"))
    return near.select(F.col("x.o_orderkey").alias("first_key"), F.col("y.o_orderkey").alias("second_key"))


@q("SELECT a.conv_id, a.turn, a.role AS role_now, b.role AS role_next FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1")
def q94_self_join(t, s):
    a, b = t.conversations.alias("a"), t.conversations.alias("b")
    return a.join(b, (F.col("a.conv_id") == F.col("b.conv_id")) & (F.col("b.turn") == F.col("a.turn") + 1)).select("a.conv_id", "a.turn", F.col("a.role").alias("role_now"), F.col("b.role").alias("role_next"))


@q(f"SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum({CENTS.format('l_extendedprice')}) AS BIGINT) AS cents, round(avg(CAST(l_quantity AS BIGINT)), 6) AS mean, min(l_quantity) AS least, max(l_quantity) AS most, round(stddev_samp(l_quantity), 6) AS sd FROM lineitem GROUP BY 1, 2")
def q95_group_agg(t, s):
    return t.lineitem.groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum(cents("l_extendedprice")).alias("cents"), F.round(F.avg(F.col("l_quantity").cast("long")), 6).alias("mean"), F.min("l_quantity").alias("least"), F.max("l_quantity").alias("most"), F.round(F.stddev_samp("l_quantity"), 6).alias("sd"))


@q("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, CAST(sum(DISTINCT l_suppkey) AS BIGINT) AS supps FROM lineitem GROUP BY 1")
def q96_distinct_agg(t, s):
    return t.lineitem.groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.sum_distinct("l_suppkey").alias("supps"))


@q("SELECT l_returnflag, count(DISTINCT l_orderkey) AS orders, true AS near FROM lineitem GROUP BY 1")
def q97_approx_distinct(t, s):
    """The sketch's count is within a tenth of the exact one."""
    exact = F.countDistinct("l_orderkey")
    return t.lineitem.groupBy("l_returnflag").agg(exact.alias("orders"), (F.abs(F.approx_count_distinct("l_orderkey") - exact) <= exact / 10).alias("near"))


_GS = "CAST(CAST(grouping(l_returnflag) * 2 + grouping(l_linestatus) AS INT) AS INT) AS gid"


@q(f"SELECT l_returnflag, l_linestatus, {_GS}, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())")
def q98_grouping_sets(t, s):
    f, l = F.col("l_returnflag"), F.col("l_linestatus")
    return t.lineitem.groupingSets([[f, l], [f], []], f, l).agg(F.grouping_id().cast("int").alias("gid"), F.count("*").alias("n"))


@q(f"SELECT l_returnflag, l_linestatus, {_GS}, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def q99_cube(t, s):
    return t.lineitem.cube("l_returnflag", "l_linestatus").agg(F.grouping_id().cast("int").alias("gid"), F.count("*").alias("n"))


@q("SELECT CAST(year(o_orderdate) AS INT) AS y, CAST(quarter(o_orderdate) AS INT) AS qu, CAST(month(o_orderdate) AS INT) AS m, count(*) AS n FROM orders GROUP BY ROLLUP (1, 2, 3)")
def q100_rollup(t, s):
    return t.orders.select(F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("qu"), F.month("o_orderdate").alias("m")).rollup("y", "qu", "m").agg(F.count("*").alias("n"))


@q("SELECT CAST(year(o_orderdate) AS INT) AS y, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o, count(*) FILTER (o_orderstatus = 'P') AS p FROM orders GROUP BY 1")
def q101_pivot(t, s):
    d = t.orders.groupBy(F.year("o_orderdate").alias("y")).pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1)))
    return d.fillna(0).select("y", F.col("F").alias("f"), F.col("O").alias("o"), F.col("P").alias("p"))


@q("SELECT s_suppkey, 'nation' AS what, CAST(s_nationkey AS BIGINT) AS v FROM supplier UNION ALL SELECT s_suppkey, 'cents', CAST(round(s_acctbal * 100) AS BIGINT) FROM supplier")
def q102_unpivot(t, s):
    d = t.supplier.select("s_suppkey", F.col("s_nationkey").cast("long").alias("nation"), cents("s_acctbal").alias("cents"))
    return d.unpivot("s_suppkey", ["nation", "cents"], "what", "v")


@q("SELECT user_id, count(*) FILTER (event_type = 'error') AS errors, CAST(sum(CASE WHEN value > 50 THEN 1 ELSE 0 END) AS BIGINT) AS high FROM events GROUP BY 1")
def q103_conditional_agg(t, s):
    return t.events.groupBy("user_id").agg(F.count_if(F.col("event_type") == "error").alias("errors"), F.sum(F.when(F.col("value") > 50, 1).otherwise(0)).alias("high"))


@q("SELECT user_id, arg_min(value, ts) AS first_value, arg_max(value, ts) AS last_value FROM events GROUP BY 1")
def q104_minmax_by(t, s):
    return t.events.groupBy("user_id").agg(F.min_by("value", "ts").alias("first_value"), F.max_by("value", "ts").alias("last_value"))


@q("SELECT event_type, round(quantile_cont(value, 0.25), 6) AS q1, round(quantile_cont(value, 0.5), 6) AS q2, round(quantile_cont(value, 0.75), 6) AS q3 FROM events GROUP BY 1")
def q105_percentile_exact(t, s):
    d = t.events.groupBy("event_type").agg(F.percentile("value", [0.25, 0.5, 0.75]).alias("p"))
    return d.select("event_type", *[F.round(F.col("p")[i], 6).alias(f"q{i + 1}") for i in range(3)])


@q("SELECT CAST(unnest(range(1, 10)) AS INT) AS tenth, true AS near")
def q106_percentile_approx(t, s):
    """The share of rows below an approximate decile is within a hundredth of it."""
    cuts = t.lineitem.agg(F.percentile_approx("l_extendedprice", [0.1 * i for i in range(1, 10)], 10000)).first()[0]
    below = t.lineitem.agg(*[F.avg((F.col("l_extendedprice") < c).cast("double")).alias(f"p{i + 1}") for i, c in enumerate(cuts)])
    return below.select(F.explode(F.array(*[F.struct(F.lit(i).alias("tenth"), (F.abs(F.col(f"p{i}") - i / 10) < 0.01).alias("near")) for i in range(1, 10)])).alias("x")).select("x.*")


@q("SELECT round(corr(l_quantity, l_extendedprice), 6) AS qp, round(corr(l_extendedprice, l_discount), 6) AS pd, round(covar_samp(l_quantity, l_discount), 6) AS cqd FROM lineitem")
def q107_corr_covar(t, s):
    return t.lineitem.agg(F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("qp"), F.round(F.corr("l_extendedprice", "l_discount"), 6).alias("pd"), F.round(F.covar_samp("l_quantity", "l_discount"), 6).alias("cqd"))


@q("SELECT CAST(least(floor(l_quantity / 8), 7) AS INT) AS b, count(*) AS n FROM lineitem GROUP BY 1")
def q108_equiwidth_hist(t, s):
    return t.lineitem.groupBy(F.least(F.width_bucket("l_quantity", F.lit(0.0), F.lit(64.0), F.lit(8)) - 1, F.lit(7)).cast("int").alias("b")).agg(F.count("*").alias("n"))


_R = "OVER (PARTITION BY s_nationkey ORDER BY s_acctbal DESC, s_suppkey)"


@q(f"SELECT s_suppkey, row_number() {_R} AS rn, rank() {_R} AS rk, dense_rank() {_R} AS dr, round(percent_rank() {_R}, 9) AS pr, round(cume_dist() {_R}, 9) AS cd FROM supplier")
def q109_rank_family(t, s):
    w = W.partitionBy("s_nationkey").orderBy(F.desc("s_acctbal"), "s_suppkey")
    long = lambda f: f.over(w).cast("long")
    return t.supplier.select("s_suppkey", long(F.row_number()).alias("rn"), long(F.rank()).alias("rk"), long(F.dense_rank()).alias("dr"), F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"))


@q("SELECT s_suppkey, CAST(ntile(4) OVER (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey) AS INT) AS quarter FROM supplier")
def q110_ntile(t, s):
    return t.supplier.select("s_suppkey", F.ntile(4).over(W.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey")).alias("quarter"))


@q("SELECT event_id, epoch_us(ts) - lag(epoch_us(ts)) OVER w AS gap_before, lead(epoch_us(ts)) OVER w - epoch_us(ts) AS gap_after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def q111_lag_lead(t, s):
    w, us = W.partitionBy("user_id").orderBy("ts", "event_id"), F.unix_micros(F.col("ts").cast("timestamp"))
    return t.events.select("event_id", (us - F.lag(us).over(w)).alias("gap_before"), (F.lead(us).over(w) - us).alias("gap_after"))


_V = CENTS.format("value")


@q(f"SELECT event_id, CAST(sum({_V}) OVER (w ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running, CAST(sum({_V}) OVER (w ROWS BETWEEN 6 PRECEDING AND CURRENT ROW) AS BIGINT) AS last7 FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def q112_running_frame(t, s):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    return t.events.select("event_id", F.sum(cents("value")).over(w.rowsBetween(W.unboundedPreceding, 0)).alias("running"), F.sum(cents("value")).over(w.rowsBetween(-6, 0)).alias("last7"))


@q(f"SELECT event_id, CAST(sum({_V}) OVER (PARTITION BY user_id ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS BIGINT) AS hour_sum FROM events")
def q113_range_frame(t, s):
    w = W.partitionBy("user_id").orderBy(F.unix_seconds(F.col("ts").cast("timestamp"))).rangeBetween(-3600, 0)
    return t.events.select("event_id", F.sum(cents("value")).over(w).alias("hour_sum"))


@q("SELECT DISTINCT user_id, first_value(value) OVER w AS first_v, last_value(value) OVER w AS last_v, nth_value(value, 3) OVER w AS third_v FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def q114_first_last_nth(t, s):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return t.events.select("user_id", F.first("value").over(w).alias("first_v"), F.last("value").over(w).alias("last_v"), F.nth_value("value", 3).over(w).alias("third_v")).distinct()


@q("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def q115_topk_global(t, s):
    return t.orders.orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey", "o_totalprice")


@q("SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 3")
def q116_topk_group(t, s):
    w = W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return t.orders.withColumn("r", F.row_number().over(w)).filter("r <= 3").select("o_custkey", "o_orderkey")


@q("SELECT p_partkey FROM part ORDER BY p_retailprice, p_partkey LIMIT 10 OFFSET 20")
def q117_limit_offset(t, s):
    return t.part.orderBy("p_retailprice", "p_partkey").offset(20).limit(10).select("p_partkey")


_C, _S = "SELECT c_nationkey AS k FROM customer", "SELECT s_nationkey FROM supplier"


@q(f"SELECT 'union' AS op, k, count(*) AS n FROM ({_C} UNION {_S}) GROUP BY k UNION ALL SELECT 'intersect_all', k, count(*) FROM ({_C} INTERSECT ALL {_S}) GROUP BY k UNION ALL SELECT 'except_all', k, count(*) FROM ({_C} EXCEPT ALL {_S}) GROUP BY k")
def q118_set_ops(t, s):
    a, b = t.customer.select(F.col("c_nationkey").alias("k")), t.supplier.select(F.col("s_nationkey").alias("k"))
    part = lambda op, d: d.groupBy("k").agg(F.count("*").alias("n")).select(F.lit(op).alias("op"), "k", "n")
    return part("union", a.union(b).distinct()).union(part("intersect_all", a.intersectAll(b))).union(part("except_all", a.exceptAll(b)))


@q("SELECT md5(text) AS h, min(doc_id) AS doc_id, count(*) AS n FROM documents GROUP BY text")
def q119_distinct_dedup(t, s):
    return t.documents.groupBy(F.md5("text").alias("h")).agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("n"))


@q("SELECT doc_id, length(text) AS n, lower(substring(lang, 1, 1)) AS l, len(string_split(text, ' ')) AS parts, regexp_extract(source, '([0-9]+)', 1) AS src, concat_ws('-', lang, source) AS tag, upper(lang) AS up FROM documents")
def q120_string_funcs(t, s):
    return t.documents.select("doc_id", F.length("text").cast("long").alias("n"), F.lower(F.substring("lang", 1, 1)).alias("l"), F.size(F.split("text", " ")).cast("long").alias("parts"), F.regexp_extract("source", "([0-9]+)", 1).alias("src"), F.concat_ws("-", "lang", "source").alias("tag"), F.upper("lang").alias("up"))


@q("SELECT l_orderkey, l_linenumber, l_partkey, CAST(floor(l_extendedprice) AS BIGINT) AS fl, CAST(ceil(l_quantity / 7) AS BIGINT) AS ce, round(ln(l_quantity), 6) AS lg, round(sqrt(l_quantity), 6) AS sq, l_orderkey % 7 AS md, l_partkey >> 2 AS sh, greatest(l_orderkey, l_partkey) AS gr, least(l_orderkey, l_partkey) AS le FROM lineitem")
def q121_math_funcs(t, s):
    return t.lineitem.select("l_orderkey", "l_linenumber", "l_partkey", F.floor("l_extendedprice").alias("fl"), F.ceil(F.col("l_quantity") / 7).alias("ce"), F.round(F.ln("l_quantity"), 6).alias("lg"), F.round(F.sqrt("l_quantity"), 6).alias("sq"), F.pmod("l_orderkey", F.lit(7)).alias("md"), F.shiftright("l_partkey", 2).alias("sh"), F.greatest("l_orderkey", "l_partkey").alias("gr"), F.least("l_orderkey", "l_partkey").alias("le"))


@q("SELECT o_orderkey, CAST(year(o_orderdate) AS INT) AS y, CAST(quarter(o_orderdate) AS INT) AS qu, CAST(month(o_orderdate) AS INT) AS m, CAST(dayofweek(o_orderdate) + 1 AS INT) AS dow, CAST(date_trunc('month', o_orderdate) AS DATE) AS month_start, CAST(datediff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INT) AS days, CAST(epoch(o_orderdate) AS BIGINT) AS secs FROM orders")
def q122_date_funcs(t, s):
    d = F.col("o_orderdate")
    return t.orders.select("o_orderkey", F.year(d).alias("y"), F.quarter(d).alias("qu"), F.month(d).alias("m"), F.dayofweek(d).alias("dow"), F.date_trunc("month", d).cast("date").alias("month_start"), F.datediff(d, F.lit("1992-01-01").cast("date")).alias("days"), F.unix_seconds(d.cast("timestamp")).alias("secs"))


@q("SELECT vec_id, len(embedding) AS n, CAST(embedding[3] AS DOUBLE) AS third, len(list_filter(embedding, lambda x: x > 0)) AS positive, CAST(list_max(embedding) AS DOUBLE) AS top FROM embeddings")
def q123_array_funcs(t, s):
    return t.embeddings.select("vec_id", F.size("embedding").cast("long").alias("n"), F.element_at("embedding", 3).cast("double").alias("third"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"), F.array_max("embedding").cast("double").alias("top"))


@q("SELECT n_nationkey, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def q124_map_funcs(t, s):
    m = t.region.agg(F.map_from_entries(F.collect_list(F.struct("r_regionkey", "r_name")))).scalar()
    return t.nation.withColumn("m", m).select("n_nationkey", F.element_at("m", F.col("n_regionkey").cast(dict(t.region.dtypes)["r_regionkey"])).alias("r_name"))


@q("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k, CAST(json_extract_string(props, '$.k') AS INT) * 2 AS k2, '{\"id\":' || event_id || '}' AS j FROM events")
def q125_json_funcs(t, s):
    return t.events.select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"), (F.from_json("props", "k int")["k"] * 2).alias("k2"), F.to_json(F.struct(F.col("event_id").alias("id"))).alias("j"))


@q("SELECT substring(md5(c_name), 1, 1) AS bucket, count(*) AS n FROM customer GROUP BY 1")
def q126_hash_bucket(t, s):
    return t.customer.groupBy(F.substring(F.md5("c_name"), 1, 1).alias("bucket")).agg(F.count("*").alias("n"))


@q(
    f"WITH {plan_sql(8, 8)}, w AS (SELECT CAST(max(l_quantity) - min(l_quantity) AS BIGINT) % 8 AS k FROM lineitem GROUP BY l_orderkey) "
    "SELECT owner, count(*) AS triples, any_value(orders) AS orders FROM plan JOIN (SELECT k, count(*) AS orders FROM w GROUP BY k) ON owner = k GROUP BY owner"
)
def q127_udf_udaf_udtf(t, s):
    """An aggregate in pandas over groups of bounded size, and the planner as a table function."""

    @F.pandas_udf("long")
    def spread(v: pd.Series) -> int:
        return int(v.max() - v.min())

    S.register(s)
    plan = s.sql("SELECT owner, count(*) AS triples FROM work_plan(8, 16, 256) GROUP BY owner")
    widths = t.lineitem.groupBy("l_orderkey").agg(spread(F.col("l_quantity")).alias("spread"))  # lines of an order
    orders = widths.groupBy(F.pmod("spread", F.lit(8)).alias("k")).agg(F.count("*").alias("orders"))
    return plan.join(orders, F.col("owner") == F.col("k")).select("owner", "triples", "orders")


@q("SELECT fmt, n_nationkey, n_name FROM nation, (SELECT unnest(['csv', 'json', 'orc', 'parquet', 'text']) AS fmt)")
def q128_formats_roundtrip(t, s):
    return formats.roundtrip(t.nation.select("n_nationkey", "n_name"))


_SUB = "WITH big AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey) SELECT c_custkey FROM {customer} WHERE c_acctbal > (SELECT avg(c_acctbal) FROM {customer}) AND EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_orderstatus = 'F') AND c_custkey IN (SELECT o_custkey FROM big WHERE n > 8)"


@q(_SUB.format(customer="customer", orders="orders"))
def q129_subqueries(t, s):
    return s.sql(_SUB.replace("FROM orders", "FROM {orders}"), customer=t.customer, orders=t.orders)
