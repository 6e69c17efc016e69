"""How well a subset stands for the corpus: transport cost, its two-term bound, and the rate in the number of clusters."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def quantisation(assigned: DataFrame) -> DataFrame:
    """Mean squared distance of the corpus to its centres."""
    return assigned.agg(F.avg(F.col("dist") * F.col("dist")).alias("quantisation"))


def gain(assigned: DataFrame, subset: DataFrame) -> DataFrame:
    """(k, n, alpha, sigma2, n_sel, sel2, gain): mass, spread, the selection's spread and the signed difference."""
    flags = subset.select("doc_id", F.lit(1).alias("__in"))
    d2 = F.col("dist") * F.col("dist")
    rows = assigned.select("doc_id", "k", "dist").join(flags, "doc_id", "left")
    by_k = rows.groupBy("k").agg(F.count(F.lit(1)).alias("n"), F.avg(d2).alias("sigma2"), F.count("__in").alias("n_sel"), F.avg(F.when(F.col("__in") == 1, d2)).alias("sel2"))
    return by_k.crossJoin(F.broadcast(by_k.agg(F.sum("n").alias("all")))).select("k", "n", (F.col("n") / F.col("all")).alias("alpha"), "sigma2", "n_sel", "sel2", (F.col("sigma2") - F.col("sel2")).alias("gain"))


def pruning(gains: DataFrame, mass: str = "corpus") -> DataFrame:
    """Spread of the selection around the same centres; by corpus masses it is null if a cluster has nothing selected."""
    if mass == "corpus":
        return gains.agg(F.when(F.sum(F.when(F.col("n_sel") == 0, 1).otherwise(0)) == 0, F.sum(F.col("alpha") * F.col("sel2"))).alias("pruning"))
    return gains.agg((F.sum(F.col("n_sel") * F.col("sel2")) / F.sum("n_sel")).alias("pruning"))


def bound(gains: DataFrame) -> DataFrame:
    """(quantisation, pruning, bound): twice the sum of both terms is at least the transport cost of the re-weighted selection."""
    q = gains.agg(F.sum(F.col("alpha") * F.col("sigma2")).alias("quantisation"))
    return q.crossJoin(pruning(gains)).withColumn("bound", 2 * F.col("quantisation") + 2 * F.col("pruning"))


def rate(curve: DataFrame) -> DataFrame:
    """(slope, dimension, constant) of log quantisation on log K."""
    x, y = F.log("K"), F.log("quantisation")
    return curve.agg(F.regr_slope(y, x).alias("slope"), F.regr_intercept(y, x).alias("b")).select("slope", (-2 / F.col("slope")).alias("dimension"), F.exp("b").alias("constant"))


def w2_sliced(a: DataFrame, b: DataFrame, directions: int = 32, grid: int = 64, d: int = 64, seed: int = 42, accuracy: int = 2000) -> DataFrame:
    """Mean over directions of the squared distance of projected quantiles, times d: a scalable stand-in for W2^2.

    Projections run in one codegen stage; each side sends one quantile sketch per direction.
    """
    rng = np.random.default_rng(seed)
    dirs = rng.normal(size=(directions, d))
    dirs /= np.linalg.norm(dirs, axis=1, keepdims=True)
    ps = [(i + 0.5) / grid for i in range(grid)]

    def sketch(df: DataFrame, name: str) -> DataFrame:
        way = F.array(*[F.array(*[F.lit(float(v)) for v in row]) for row in dirs])
        proj = df.select(F.posexplode(F.transform(way, lambda w: F.aggregate(F.zip_with("emb", w, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x))).alias("dir", "x"))
        return proj.groupBy("dir").agg(F.percentile_approx("x", ps, accuracy).alias(name))

    both = sketch(a, "qa").join(sketch(b, "qb"), "dir")
    gap = F.aggregate(F.zip_with("qa", "qb", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x) / grid
    return both.agg((F.avg(gap) * d).alias("w2_sliced"))


def w2_exact(x: np.ndarray, a: np.ndarray, y: np.ndarray, b: np.ndarray) -> float:
    """Exact squared W2 of two small weighted point sets, by successive shortest paths (tests only)."""
    cost = ((x[:, None, :] - y[None, :, :]) ** 2).sum(-1)
    n, m = cost.shape
    left, right = a.astype(float).copy(), b.astype(float).copy()
    flow = np.zeros((n, m))
    u, v = np.zeros(n), np.zeros(m)
    while left.max() > 1e-12:
        # Dijkstra from all rows with supply, on reduced costs
        du, dv = np.where(left > 1e-12, 0.0, np.inf), np.full(m, np.inf)
        pu, pv = np.full(n, -1), np.full(m, -1)
        done_u, done_v = np.zeros(n, bool), np.zeros(m, bool)
        while True:
            iu = int(np.argmin(np.where(done_u, np.inf, du)))
            iv = int(np.argmin(np.where(done_v, np.inf, dv)))
            best_u = du[iu] if not done_u[iu] else np.inf
            best_v = dv[iv] if not done_v[iv] else np.inf
            if not np.isfinite(min(best_u, best_v)):
                break
            if best_u <= best_v:
                done_u[iu] = True
                alt = du[iu] + np.maximum(cost[iu] + u[iu] - v, 0)
                better = (alt < dv - 1e-15) & ~done_v
                dv[better], pv[better] = alt[better], iu
            else:
                done_v[iv] = True
                back = np.flatnonzero((flow[:, iv] > 1e-15) & ~done_u)
                alt = dv[iv] + np.maximum(v[iv] - u[back] - cost[back, iv], 0)
                better = alt < du[back] - 1e-15
                du[back[better]], pu[back[better]] = alt[better], iv
        end = int(np.argmin(np.where(right > 1e-12, dv, np.inf)))
        u += np.where(np.isfinite(du), du, 0)
        v += np.where(np.isfinite(dv), dv, 0)
        path, j = [], end
        while True:
            i = pv[j]
            path.append((i, j, 1))
            if pu[i] < 0:
                break
            path.append((i, pu[i], -1))
            j = pu[i]
        amount = min([left[path[-1][0]], right[end], *[flow[i, j] for i, j, s in path if s < 0]])
        for i, j, s in path:
            flow[i, j] += s * amount
        left[path[-1][0]] -= amount
        right[end] -= amount
    return float((flow * cost).sum())
