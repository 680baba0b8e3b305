"""Queries q21 - q25: ownership of triples and what it makes of the rows."""

from __future__ import annotations

from pyspark.sql import functions as F

from cubelens.operators import cube
from cubelens.operators.metrics import unit_loads
from cubelens.plans import triples as T
from cubelens.queries import base as Q
from cubelens.sources import catalog as C

queries, oracles = {}, {}


def plan_sql(n: int, r: int) -> str:
    """The plan in SQL: rounds by the smallest member, then the rule for three, two or one member below the owners."""
    return f"""
t AS (SELECT a.i AS d0, b.i AS d1, c.i AS d2, row_number() OVER (ORDER BY a.i, b.i, c.i) - 1 AS triple
  FROM (SELECT unnest(range({n})) AS i) a, (SELECT unnest(range({n})) AS i) b, (SELECT unnest(range({n})) AS i) c WHERE a.i < b.i AND b.i < c.i),
o AS (SELECT *, (d0 // {r}) * {r} AS base, least({r}, {n} - (d0 // {r}) * {r}) AS r FROM t),
h AS (SELECT *, d0 - base AS a, d1 - base AS b, d2 - base AS c FROM o),
g AS (SELECT *, (b - a) * 10000 + (c - b) * 100 + (r - c + a) AS ga, (c - b) * 10000 + (r - c + a) * 100 + (b - a) AS gb, (r - c + a) * 10000 + (b - a) * 100 + (c - b) AS gc FROM h),
plan AS (SELECT CAST(triple AS INT) AS triple, CAST(d0 AS INT) AS d0, CAST(d1 AS INT) AS d1, CAST(d2 AS INT) AS d2, CAST(d0 // {r} AS INT) AS round, CAST(base + CASE
  WHEN c < r THEN CASE WHEN ga <= gb AND ga <= gc THEN a WHEN gb <= gc THEN b ELSE c END
  WHEN b < r THEN CASE WHEN 2 * (b - a) < r OR 2 * (b - a) = r AND (c - r) % 2 = 1 THEN a ELSE b END
  ELSE a END AS INT) AS owner FROM g)"""


#: The line items that a plan is for: every row is an update of each triple that has one.
ROWS_SQL = "(SELECT count(l_orderkey) AS rows FROM lineitem)"


def with_rows(spark, sf, frame):
    """``frame`` beside the number of line items with an order, counted from the column."""
    counted = C.table(spark, sf, "lineitem").agg(F.count("l_orderkey").alias("rows"))
    return frame.crossJoin(F.broadcast(counted))  # one row


def _plan(name, n, r):
    queries[name] = lambda spark, sf: with_rows(spark, sf, T.plan_frame(spark, T.plan_rounds(n, r)))
    oracles[name] = f"WITH {plan_sql(n, r)} SELECT plan.*, rows FROM plan, {ROWS_SQL}"


_plan("q21_plan_owner", 24, 24)
_plan("q22_plan_rounds", 32, 6)


def q23_plan_pairs(spark, sf):
    return with_rows(spark, sf, spark.createDataFrame(T.plan_pairs(16), "i int, j int, owner int"))


oracles["q23_plan_pairs"] = "SELECT CAST(a.i AS INT) AS i, CAST(b.i AS INT) AS j, CAST(CASE WHEN 2 * (b.i - a.i) < 16 OR 2 * (b.i - a.i) = 16 AND a.i % 2 = 0 THEN a.i ELSE b.i END AS INT) AS owner, rows FROM (SELECT unnest(range(16)) AS i) a, (SELECT unnest(range(16)) AS i) b, " + ROWS_SQL + " WHERE a.i < b.i"


def q24_plan_balance(spark, sf):
    plan = T.plan_frame(spark, T.plan_rounds(32, 16))
    own = plan.groupBy("round", "owner").agg(F.count("*").alias("n"))
    out = with_rows(spark, sf, own.groupBy("round").agg(F.count("*").alias("owners"), F.min("n").alias("least"), F.max("n").alias("most")))
    return out.select("round", "owners", "least", "most", (F.col("most") * F.col("rows")).alias("updates"))


oracles["q24_plan_balance"] = f"WITH {plan_sql(32, 16)}, o2 AS (SELECT round, owner, count(*) AS n FROM plan GROUP BY ALL) SELECT round, count(*) AS owners, min(n) AS least, max(n) AS most, max(n) * any_value(rows) AS updates FROM o2, {ROWS_SQL} GROUP BY round"


def q25_routing_counts(spark, sf):
    rows = cube.narrow(Q.binned(spark, sf, Q.DIMS, Q.BINS), Q.DIMS)
    return unit_loads(cube.route(rows, Q.DIMS, list(range(len(Q.DIMS)))))


oracles["q25_routing_counts"] = f"WITH {Q.binned_sql(Q.DIMS, Q.BINS)} " + " UNION ALL ".join(f"SELECT {k} AS owner, {s.bin} AS owner_bin, count(*) AS rows FROM binned GROUP BY 2" for k, s in enumerate(Q.DIMS))

for _f in (q23_plan_pairs, q24_plan_balance, q25_routing_counts):
    queries[_f.__name__] = _f
