"""All registered queries of the method and its surroundings."""

from __future__ import annotations

import importlib

from pyspark.sql import DataFrame, SparkSession

from cubelens.explore import explore
from cubelens.queries import base

MODULES = ("normal", "plan", "cubes", "experiments", "images", "scenarios", "surround", "stream")


def _modules():
    return [importlib.import_module(f"cubelens.queries.{m}") for m in MODULES]


def queries() -> dict:
    return {k: v for m in _modules() for k, v in m.queries.items()}


def oracle_sql() -> dict[str, str]:
    return {k: v for m in _modules() for k, v in m.oracles.items()}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ranked images of six dimensions of the order star, 8 bins, 4 slabs."""
    return explore(base.facts(spark, sf_dir), base.DIMS, base.C.STAR_KEY, bins=base.BINS, m=10, n=2)
