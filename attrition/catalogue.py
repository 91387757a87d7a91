"""The registry of named queries and of the SQL that each must equal."""

from __future__ import annotations

from collections.abc import Callable
from importlib import import_module

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]
PARTS = ("graph_queries", "usage_queries", "model_queries", "experiment_queries", "relational_queries")


def queries() -> dict[str, Query]:
    return {k: q for p in PARTS for k, q in import_module(f"attrition.plans.{p}").QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {k: q for p in PARTS for k, q in import_module(f"attrition.plans.{p}").ORACLES.items()}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row for each home number of the contact graph: ranks, structure and best similarities."""
    return queries()["graph_features"](spark, sf_dir)
