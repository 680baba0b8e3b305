"""The given tables as two wide fact tables with their declared dimensions."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cubelens.dimension import DimensionSpec as D
from cubelens.dimension import MeasureSpec


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Columns that identify a line item, by which ties are broken.
STAR_KEY = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "cents")
LOG_KEY = ("event_id",)

#: The order star as SQL that both engines read.
STAR_SQL = """SELECT l.*, CAST(round(l_extendedprice * 100) AS BIGINT) AS cents, o.o_custkey, o.o_orderstatus, o.o_totalprice, o.o_orderdate, o.o_orderpriority,
  c.c_name, c.c_nationkey, c.c_acctbal, c.c_mktsegment, s.s_nationkey, s.s_acctbal, p.p_name, p.p_brand, p.p_type, p.p_size, p.p_retailprice,
  n.n_name AS c_nation, r.r_name AS c_region
FROM lineitem l JOIN orders o ON l.l_orderkey = o.o_orderkey JOIN customer c ON o.o_custkey = c.c_custkey
  JOIN supplier s ON l.l_suppkey = s.s_suppkey JOIN part p ON l.l_partkey = p.p_partkey
  JOIN nation n ON c.c_nationkey = n.n_nationkey JOIN region r ON n.n_regionkey = r.r_regionkey"""

STAR_DIMS = [
    D("price", ("l_extendedprice",)),
    D("net_revenue", ("l_extendedprice * (1 - l_discount)",)),
    D("quantity", ("l_quantity",)),
    D("discount", ("l_discount + 0.0",)),
    D("ship_time", ("l_shipdate",)),
    D("part_key", ("l_partkey",)),
    D("retail_price", ("p_retailprice",)),
    D("total_price", ("o_totalprice",)),
    D("order_time", ("o_orderdate",)),
    D("unit_price", ("l_extendedprice / l_quantity",)),
    D("return_flag", ("l_returnflag",)),
    D("line_status", ("l_linestatus",)),
    D("cust_balance", ("c_acctbal",)),
    D("cust_nation", ("c_nationkey",)),
    D("part_size", ("p_size",)),
    D("priority", ("o_orderpriority",)),
    D("tax", ("l_tax + 0.0",)),
    D("order_status", ("o_orderstatus",)),
    D("segment", ("c_mktsegment",)),
    D("supp_balance", ("s_acctbal",)),
    D("supp_key", ("l_suppkey",)),
    D("supp_nation", ("s_nationkey",)),
    D("brand", ("p_brand",)),
    D("part_type", ("p_type",)),
    D("part_name", ("p_name",)),
    D("order_key", ("l_orderkey",)),
    D("cust_key", ("o_custkey",)),
    D("line_number", ("l_linenumber",)),
    D("discount_by_time", ("l_discount + 0.0", "l_shipdate")),
    D("flag_by_time", ("l_returnflag", "l_shipdate")),
    D("cust_geo", ("c_region", "c_nationkey")),
    D("segment_by_balance", ("c_mktsegment", "c_acctbal")),
]
STAR = {d.name: d for d in STAR_DIMS}
#: The same attribute in other orders.
NATION_BY_NAME = D("nation_by_name", ("c_nation",))
NATION_BY_BALANCE = D("nation_by_balance", ("nation_balance",))

CENTS = MeasureSpec("cents", "cents")
UNITS = MeasureSpec("units", "CAST(l_quantity AS BIGINT)")
PRICE_FLOAT = MeasureSpec("price", "CAST(CAST(l_extendedprice AS FLOAT) AS DOUBLE)", False)
QUANTITY_DOUBLE = MeasureSpec("quantity", "l_quantity", False)


def order_star(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem with the attributes of its order, customer, supplier and part; lookups are small against the facts.

    Joins are declared; whether one side is broadcast is left to its size.
    """
    t = lambda n: table(spark, sf_dir, n)
    geo = t("nation").join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", F.col("n_name").alias("c_nation"), F.col("r_name").alias("c_region"))
    return (
        t("lineitem")
        .withColumn("cents", F.round(F.col("l_extendedprice") * 100).cast("long"))
        .join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey"))
        .join(t("customer"), F.col("o_custkey") == F.col("c_custkey"))
        .join(t("supplier").select("s_suppkey", "s_nationkey", "s_acctbal"), F.col("l_suppkey") == F.col("s_suppkey"))
        .join(t("part"), F.col("l_partkey") == F.col("p_partkey"))
        .join(geo, F.col("c_nationkey") == F.col("n_nationkey"))
        .drop("o_orderkey", "c_custkey", "s_suppkey", "p_partkey", "n_nationkey")
    )


#: Slices in which the star is joined where only few of its columns are wanted.
SLICES = 4


def order_star_slices(spark: SparkSession, sf_dir: str, columns: list[str], slices: int = SLICES) -> Iterator[DataFrame]:
    """``columns`` of ``order_star``, one slice of the orders after another; together all rows, once.

    Orders meet their customers before the line items, so that these move once for the
    orders and once more for the parts. What a slice's joins exchange is a share of it all.
    """
    t = lambda n: table(spark, sf_dir, n)
    geo = t("nation").join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", F.col("n_name").alias("c_nation"), F.col("r_name").alias("c_region"))
    for k in range(slices):
        mine = lambda d, key: d.filter(F.pmod(F.xxhash64(F.col(key).cast("long")), F.lit(slices)) == k)  # noqa: E731, B023
        orders = mine(t("orders"), "o_orderkey").join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(geo, F.col("c_nationkey") == F.col("n_nationkey"))
        facts = (
            mine(t("lineitem"), "l_orderkey")
            .withColumn("cents", F.round(F.col("l_extendedprice") * 100).cast("long"))
            .join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
            .join(t("supplier").select("s_suppkey", "s_nationkey", "s_acctbal"), F.col("l_suppkey") == F.col("s_suppkey"))
            .join(t("part"), F.col("l_partkey") == F.col("p_partkey"))
        )
        yield facts.select(*columns)


#: The activity log as SQL that both engines read; micros counts from the epoch.
LOG_SQL = """SELECT e.*, {micros} - lag({micros}) OVER w AS gap_prev, lead({micros}) OVER w - {micros} AS gap_next,
  CAST(extract(hour FROM ts) * 60 + extract(minute FROM ts) AS INT) AS minute_of_day, CAST(extract(hour FROM ts) AS INT) AS hour_of_day, {dow} AS dow,
  CAST(extract(day FROM ts) AS INT) AS day_of_month, CAST(floor(extract(second FROM ts)) AS INT) AS second_of_minute, {k} AS k,
  value - lag(value) OVER w AS value_delta, row_number() OVER w AS nth, {cents} AS value_cents,
  sum({cents}) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS running_cents,
  c_acctbal, c_nationkey, c_mktsegment
FROM events e JOIN customer c ON e.user_id = c.c_custkey WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)"""
_CENTS = "CAST(round(value * 100) AS BIGINT)"
LOG_SPARK = LOG_SQL.format(micros="unix_micros(CAST(ts AS TIMESTAMP))", dow="dayofweek(ts) - 1", k="CAST(get_json_object(props, '$.k') AS INT)", cents=_CENTS)
LOG_DUCK = LOG_SQL.format(micros="epoch_us(ts)", dow="CAST(extract(dow FROM ts) AS INT)", k="CAST(json_extract_string(props, '$.k') AS INT)", cents=_CENTS)

LOG_DIMS = [
    D("value", ("value",)),
    D("gap_prev", ("gap_prev",)),
    D("minute_of_day", ("minute_of_day",)),
    D("hour", ("hour_of_day",)),
    D("dow", ("dow",)),
    D("day_of_month", ("day_of_month",)),
    D("ts", ("ts",)),
    D("event_type", ("event_type",)),
    D("user_id", ("user_id",)),
    D("k", ("k",)),
    D("second", ("second_of_minute",)),
    D("value_delta", ("value_delta",)),
    D("gap_next", ("gap_next",)),
    D("nth", ("nth",)),
    D("running_value", ("running_cents",)),
    D("balance", ("c_acctbal",)),
    D("nation", ("c_nationkey",)),
    D("segment", ("c_mktsegment",)),
    D("jump", ("abs(value_delta)",)),
    D("value_down", ("value desc",)),
    D("week_time", ("dow", "minute_of_day")),
    D("type_by_value", ("event_type", "value")),
    D("type_by_time", ("event_type", "ts")),
    D("hour_by_value", ("hour_of_day", "value")),
]
LOG = {d.name: d for d in LOG_DIMS}


def activity_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """events with gaps, running totals and the user's attributes; a user's first event has null gaps."""
    return spark.sql(LOG_SPARK.replace("FROM events e", "FROM {events} e").replace("JOIN customer c", "JOIN {customer} c"), events=table(spark, sf_dir, "events"), customer=table(spark, sf_dir, "customer"))
