"""Registered queries: Spark callables and, where SQL can say the same, DuckDB statements."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from curator.plans.workloads import WORKLOADS
from curator.queries import core, relational

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = core.QUERIES | relational.QUERIES | WORKLOADS
ORACLES: dict[str, str] = core.ORACLES | relational.ORACLES


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Macro shares, micro weights, quotas and a keyed draw over the corpus with given vectors."""
    return core.curate_given_clusters(spark, sf_dir)
