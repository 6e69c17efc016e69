"""Scores of clusters and their shares of the budget."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def score(z: DataFrame, w: dict[str, float], name: str = "s") -> DataFrame:
    """Tightness counts for a cluster; size, length and language mixture against it."""
    value: Column = F.lit(w["coh"]) * F.col("zn_coh")
    for f in ("size", "len", "ent"):
        value = value - F.lit(w[f]) * F.col(f"zn_{f}")
    return z.withColumn(name, value)


def budget(scores: DataFrame, temperature: float = 1.0, name: str = "r") -> DataFrame:
    """Softmax of the scores over all rows (a table with a row per cluster)."""
    top = scores.agg(F.max("s").alias("top"))
    raised = scores.crossJoin(F.broadcast(top)).withColumn(name, F.exp((F.col("s") - F.col("top")) / F.lit(temperature))).drop("top")
    return raised.crossJoin(F.broadcast(raised.agg(F.sum(name).alias("all")))).withColumn(name, F.col(name) / F.col("all")).drop("all")


def uniform(clusters: DataFrame, name: str = "r") -> DataFrame:
    """The same share for each cluster."""
    return clusters.crossJoin(F.broadcast(clusters.agg(F.count(F.lit(1)).alias("all")))).withColumn(name, 1 / F.col("all")).drop("all")
