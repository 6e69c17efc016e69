"""Choosing the number of clusters: do scores keep their ranking when the resolution changes?"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from curator.functions.vectors import dot

SCALE = 20.0


def bridge(coarse: DataFrame, fine: DataFrame, scale: float = SCALE) -> DataFrame:
    """(i, mu) and (j, mu) -> (i, j, pi): for each coarse cluster a softmax over fine ones of scale x cosine."""
    pairs = coarse.select("i", F.col("mu").alias("a")).crossJoin(F.broadcast(fine.select("j", F.col("mu").alias("b"))))
    w = Window.partitionBy("i")
    pairs = pairs.select("i", "j", dot(F.col("a"), F.col("b")).alias("c"))
    raised = pairs.withColumn("e", F.exp(F.lit(scale) * (F.col("c") - F.max("c").over(w))))
    return raised.select("i", "j", (F.col("e") / F.sum("e").over(w)).alias("pi"))


def reconstruct(pi: DataFrame, fine_scores: DataFrame) -> DataFrame:
    """(i, s_hat): the fine scores expected under each coarse cluster's bridge row."""
    return pi.join(F.broadcast(fine_scores.select("j", "s")), "j").groupBy("i").agg(F.sum(F.col("pi") * F.col("s")).alias("s_hat"))


def _signs(df: DataFrame, x: str, y: str, order: str) -> DataFrame:
    a = df.select(F.col(order).alias("o1"), F.col(x).alias("x1"), F.col(y).alias("y1"))
    b = df.select(F.col(order).alias("o2"), F.col(x).alias("x2"), F.col(y).alias("y2"))
    pairs = a.join(F.broadcast(b), F.col("o1") < F.col("o2"))
    return pairs.select(F.signum(F.col("x1") - F.col("x2")).alias("dx"), F.signum(F.col("y1") - F.col("y2")).alias("dy"))


def tau(df: DataFrame, x: str = "s", y: str = "s_hat", order: str = "i", variant: str = "b") -> DataFrame:
    """One row with Kendall's tau of two columns over a row-per-cluster table; null where it is undefined.

    b: ties shrink the denominator of their own side.  a: over all pairs.
    """
    d = _signs(df, x, y, order)
    out: Column = F.sum(F.col("dx") * F.col("dy"))
    if variant == "a":
        value = out / F.nullif(F.count(F.lit(1)), F.lit(0))
    else:
        value = out / F.nullif(F.sqrt(F.sum(F.abs("dx")) * F.sum(F.abs("dy"))), F.lit(0.0))
    return d.agg(value.alias("tau"))


def tau_value(x: np.ndarray, y: np.ndarray, variant: str = "b") -> float | None:
    """The same for numbers on the driver; 'weighted' gives pairs of high scores more weight (1/(rank+1) summed)."""
    i, j = np.triu_indices(len(x), 1)
    if not len(i):
        return None
    dx, dy = np.sign(x[i] - x[j]), np.sign(y[i] - y[j])
    w = np.ones(len(i))
    if variant == "weighted":
        rank = np.argsort(np.argsort(-x, kind="stable"), kind="stable")
        w = 1 / (rank[i] + 1) + 1 / (rank[j] + 1)
    top = (w * dx * dy).sum()
    below = w.sum() if variant == "a" else np.sqrt((w * abs(dx)).sum() * (w * abs(dy)).sum())
    return float(top / below) if below > 0 else None


def choose(curve: list[tuple[int, float | None]], rule: str = "argmax", tol: float = 0.02) -> int | None:
    """argmax: the smallest K of the highest stability; plateau: the smallest K within tol of it."""
    known = [(k, j) for k, j in curve if j is not None]
    if not known:
        return None
    top = max(j for _, j in known)
    return min(k for k, j in known if j >= top - (tol if rule == "plateau" else 0.0))


def gain(curve: DataFrame) -> DataFrame:
    """Adds dJ, the change from the K before (a row per grid point)."""
    return curve.withColumn("dJ", F.col("J") - F.lag("J").over(Window.orderBy("K")))
