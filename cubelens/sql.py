"""The method for SQL users: scalar functions, table functions and views."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from cubelens.plans.triples import owners_for, plan_rounds, triples_of


@udtf(returnType="triple int, d0 int, d1 int, d2 int")
class Triples:
    def eval(self, n: int):
        for k, t in enumerate(triples_of(n)):
            yield (k, *t)


@udtf(returnType="triple int, d0 int, d1 int, d2 int, round int, owner int")
class WorkPlan:
    def eval(self, n: int, bins: int, units: int):
        for p in plan_rounds(n, owners_for(units, bins)):
            yield (p.triple, *p.dims, p.round, p.owner)


def register(spark: SparkSession, views: dict[str, DataFrame] | None = None) -> None:
    """Temporary functions heat_red and heat_blue (plain SQL, no Python in the plan), triples and work_plan, and views."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION heat_red(v DOUBLE, s DOUBLE) RETURNS DOUBLE RETURN CASE WHEN s > 0 AND v > s THEN least(1D, v / s - 1) ELSE 0D END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION heat_blue(v DOUBLE, s DOUBLE) RETURNS DOUBLE RETURN CASE WHEN s > 0 AND v <= s THEN least(1D, 1 - v / s) ELSE 0D END")
    spark.udtf.register("triples", Triples)
    spark.udtf.register("work_plan", WorkPlan)
    for name, df in (views or {}).items():
        df.createOrReplaceTempView(name)
