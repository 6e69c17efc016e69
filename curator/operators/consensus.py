"""Consensus weights: how far the oriented features agree over the clusters of one resolution.

The published formula is not in the text at hand; this is a reconstruction.  Tightness counts with a plus, the
other three with a minus; the agreement of two features is (1 + correlation) / 2, which makes a non-negative matrix
whose leading eigenvector, scaled to sum one, gives the weights.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from curator.operators.features import FEATURES

SIGNS = {"coh": 1.0, "size": -1.0, "len": -1.0, "ent": -1.0}


def safe_corr(x: str, y: str):
    """Correlation, null where a side is constant (the built-in one divides by zero there in ANSI mode)."""
    spread = F.stddev_pop(x) * F.stddev_pop(y)
    return F.covar_pop(x, y) / F.when(spread > 1e-12, spread)


def correlations(z: DataFrame, method: str = "pearson") -> DataFrame:
    """(f, g, rho) of the oriented normalised features, all sixteen; 0 where a feature is constant, 1 on the diagonal."""
    cols = {n: f"zn_{n}" for n in FEATURES}
    if method == "spearman":
        from pyspark.sql import Window

        for n in FEATURES:
            z = z.withColumn(f"rk_{n}", F.rank().over(Window.orderBy(f"zn_{n}")))
        cols = {n: f"rk_{n}" for n in FEATURES}
    pairs = [(f, g) for f in FEATURES for g in FEATURES]
    got = z.agg(*[safe_corr(cols[f], cols[g]).alias(f"{f}_{g}") for f, g in pairs])
    rho = lambda f, g: F.lit(1.0) if f == g else F.coalesce(F.col(f"{f}_{g}"), F.lit(0.0)) * (SIGNS[f] * SIGNS[g])
    return got.select(F.explode(F.array(*[F.struct(F.lit(f).alias("f"), F.lit(g).alias("g"), rho(f, g).alias("rho")) for f, g in pairs])).alias("x")).select("x.f", "x.g", "x.rho")


def affinity(rho: np.ndarray, kind: str = "shifted") -> np.ndarray:
    return {"shifted": (1 + rho) / 2, "abs": np.abs(rho), "relu": np.maximum(rho, 0)}[kind]


def leading(a: np.ndarray) -> np.ndarray:
    """Leading eigenvector, non-negative, summing to one."""
    v = np.abs(np.linalg.eigh(a)[1][:, -1])
    return v / v.sum()


def power(a: np.ndarray, steps: int = 30) -> np.ndarray:
    """The same by a fixed number of power steps from the even vector, as SQL can do it."""
    v = np.full(len(a), 1 / len(a))
    for _ in range(steps):
        v = a @ v
        v /= v.sum()
    return v


def weights_of(zn: dict[str, np.ndarray], how: str = "spectral", kind: str = "shifted") -> dict[str, float]:
    """The same as :func:`weights` by Pearson's correlation, for normalised features that are on the driver (a number per cluster)."""
    if how == "uniform":
        return dict.fromkeys(FEATURES, 0.25)
    x = np.array([SIGNS[f] * np.asarray(zn[f], dtype=float) for f in FEATURES])
    x = x - x.mean(axis=1, keepdims=True)
    sd = x.std(axis=1)
    spread = np.outer(sd, sd)
    rho = np.where(spread > 1e-12, x @ x.T / x.shape[1] / np.where(spread > 1e-12, spread, 1.0), 0.0)
    np.fill_diagonal(rho, 1.0)
    a = affinity(rho, kind)
    return dict(zip(FEATURES, (leading(a) if how == "spectral" else power(a)).tolist(), strict=True))


def weights(z: DataFrame, how: str = "spectral", kind: str = "shifted", method: str = "pearson", given: dict[str, float] | None = None) -> dict[str, float]:
    """Weight of each feature.  how: 'spectral', 'power', 'uniform' or 'given'.  Sixteen numbers reach the driver."""
    if how == "given":
        return {n: given[n] / sum(given.values()) for n in FEATURES}
    if how == "uniform":
        return dict.fromkeys(FEATURES, 0.25)
    rho = {(r["f"], r["g"]): r["rho"] for r in correlations(z, method).collect()}
    a = affinity(np.array([[rho[f, g] for g in FEATURES] for f in FEATURES]), kind)
    return dict(zip(FEATURES, (leading(a) if how == "spectral" else power(a)).tolist(), strict=True))
