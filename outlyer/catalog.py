"""All queries of the library and their SQL twins, gathered from the modules that define them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .plans import dataflow, experiments, methods, relational


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Twenty points of the planted segments that are easiest to isolate."""
    return queries()["hash_forest_scores"](spark, sf_dir).orderBy(F.desc("score"), "pid").limit(20)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return relational.QUERIES | methods.QUERIES | experiments.QUERIES | dataflow.QUERIES


def oracle_sql() -> dict[str, str]:
    return relational.SQL | methods.SQL | experiments.SQL | dataflow.SQL
