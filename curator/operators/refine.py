"""Sub-clusters inside each cluster, and their weights: semantic score x structural penalty x cohesion gate."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from curator.functions.keyed import SEED, draw, key32
from curator.functions.vectors import unit
from curator.functions.workspace import release, stash
from curator.operators.lloyd import _nearest, matrix

LAMBDA, EPSILON = 0.5, 0.01


def sub_counts(sizes: DataFrame, c: float = 1.0, cap: int | None = None) -> DataFrame:
    """(k, n) -> (k, n, m): number of sub-clusters, ceil(c * sqrt(n)), at least 1 and at most ``cap``."""
    m = F.greatest(F.ceil(F.lit(c) * F.sqrt(F.col("n").cast("double"))).cast("int"), F.lit(1))
    return sizes.withColumn("m", F.least(m, F.lit(cap)) if cap else m)


def _fit_local(x: np.ndarray, m: int, iters: int) -> np.ndarray:
    mu = x[:m].copy()
    for _ in range(iters):
        k, _ = _nearest(x, mu)
        order = np.argsort(k, kind="stable")
        ks, at = np.unique(k[order], return_index=True)
        mean = np.add.reduceat(x[order], at, axis=0) / np.bincount(k, minlength=len(mu))[ks][:, None]
        length = np.linalg.norm(mean, axis=1, keepdims=True)
        new = mu.copy()
        new[ks] = np.where(length > 0, mean / np.maximum(length, 1e-300), mu[ks])
        if np.allclose(new, mu, atol=1e-7):
            break
        mu = new
    return mu


def _fit_shared(sample: DataFrame, parents: DataFrame, parts: Column, iters: int) -> DataFrame:
    """(k, j, mu) by the same steps as :func:`_fit_local`, for parents too large for a task.

    All parents advance together: a task holds one part of a parent's rows and that parent's centres, and sends back a
    partial sum for each centre.  Centres are a written table; none reaches the driver.
    """
    sample = stash(sample.withColumn("salt", F.pmod(F.xxhash64("doc_id"), parts).cast("int")), "sub-sample")
    d = len(sample.select("emb").first()[0])
    salts = F.broadcast(parents.select("k", F.explode(F.sequence(F.lit(0), parts - 1)).alias("salt")))
    order = Window.partitionBy("k").orderBy("h", "doc_id")
    first = sample.select("k", "m", "h", "doc_id").withColumn("j", F.row_number().over(order) - 1).where("j < m").select("doc_id", "j")
    centres = stash(sample.join(first, "doc_id").select("k", "j", F.col("emb").alias("mu")), "sub-centres")

    def sums(rows: pa.Table, mus: pa.Table) -> pa.Table:
        mus = mus.sort_by("j")
        x, mu = matrix(rows["emb"]), matrix(mus["mu"])
        if not len(x):
            return pa.table({"k": pa.array([], pa.int32()), "j": pa.array([], pa.int32()), "s": pa.array([], pa.list_(pa.float64())), "c": pa.array([], pa.int64())})
        j, _ = _nearest(x, mu)
        order = np.argsort(j, kind="stable")
        js, at = np.unique(j[order], return_index=True)
        total = np.add.reduceat(x[order], at, axis=0)
        return pa.table({"k": pa.array([rows["k"][0].as_py()] * len(js), pa.int32()), "j": pa.array(js, pa.int32()), "s": pa.array(total.tolist(), pa.list_(pa.float64())), "c": pa.array(np.bincount(j)[js])})

    rows = sample.select("k", "salt", "emb")
    for _ in range(iters):
        spread = centres.join(salts, "k")
        got = rows.groupBy("k", "salt").cogroup(spread.groupBy("k", "salt")).applyInArrow(sums, "k int, j int, s array<double>, c long")
        mean = got.groupBy("k", "j").agg(F.array(*[F.sum(F.col("s")[i]) / F.sum("c") for i in range(d)]).alias("m"))
        new = centres.join(mean, ["k", "j"], "left")
        length = F.sqrt(F.aggregate("m", F.lit(0.0), lambda a, v: a + v * v))
        new = stash(new.select("k", "j", F.when(length > 0, unit(F.col("m"), d)).otherwise(F.col("mu")).alias("mu")), "sub-centres")
        release(centres)
        centres = new
    release(sample)
    return centres


def subcluster(assigned: DataFrame, counts: DataFrame, iters: int = 8, per_centre: int = 200, rows_per_task: int = 200_000, seed: int = SEED) -> DataFrame:
    """(doc_id, k, emb, ...) -> the same with j and dist_sub.

    Each parent is fitted on a keyed sample of at most about ``per_centre`` rows for each of its sub-clusters: in one
    task if that are at most ``rows_per_task`` rows, else in shared scans.  Then all rows meet their own parent's centres
    only, parents split into salted parts of about ``rows_per_task`` rows, so no task holds a whole hot parent or the
    centres of others.  ``counts`` has a row for each parent.
    """
    sized = assigned.join(F.broadcast(counts.select("k", "n", "m")), "k")
    share = F.least(F.lit(1.0), F.lit(float(per_centre)) * F.col("m") / F.col("n"))
    sample = sized.where(draw("doc_id", seed, "sub") < share).select("k", "n", "m", "emb", key32("doc_id", seed, "sub seeds").alias("h"), "doc_id")
    rows_of = F.least(F.col("n").cast("double"), F.lit(float(per_centre)) * F.col("m"))
    large = rows_of > rows_per_task

    def fit(table: pa.Table) -> pa.Table:
        table = table.sort_by([("h", "ascending"), ("doc_id", "ascending")])
        x, m, k = matrix(table["emb"]), table["m"][0].as_py(), table["k"][0].as_py()
        mu = _fit_local(x, min(m, len(x)), iters)
        return pa.table({"k": pa.array([k] * len(mu), pa.int32()), "j": pa.array(range(len(mu)), pa.int32()), "mu": pa.array(mu.tolist(), pa.list_(pa.float64()))})

    centres = sample.where(~large).drop("n").groupBy("k").applyInArrow(fit, "k int, j int, mu array<double>")
    if not counts.where(large).isEmpty():
        shared = _fit_shared(sample.where(large), counts.where(large), F.greatest(F.ceil(rows_of / F.lit(rows_per_task)).cast("int"), F.lit(1)), iters)
        centres = centres.unionByName(shared)
    parts = F.greatest(F.ceil(F.col("n") / F.lit(rows_per_task)).cast("int"), F.lit(1))
    salted = sized.withColumn("salt", F.pmod(F.xxhash64("doc_id"), parts).cast("int")).drop("n", "m")
    names = [c for c in salted.columns if c != "salt"]
    spread = centres.join(F.broadcast(counts.select("k", F.explode(F.sequence(F.lit(0), parts - 1)).alias("salt"))), "k")

    def place(rows: pa.Table, mus: pa.Table) -> pa.Table:
        mus = mus.sort_by("j")
        x = matrix(rows["emb"])
        if len(mus) and len(x):
            j, d = _nearest(x, matrix(mus["mu"]))
        else:  # a parent none of whose rows was sampled is one sub-cluster
            j, d = np.zeros(len(x), dtype=np.int32), rows["dist"].to_numpy() if "dist" in rows.column_names else np.zeros(len(x))
        return rows.select(names).append_column("j", pa.array(j, pa.int32())).append_column("dist_sub", pa.array(d, pa.float64()))

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in salted.select(names).schema.fields)
    return salted.groupBy("k", "salt").cogroup(spread.groupBy("k", "salt")).applyInArrow(place, f"{fields}, j int, dist_sub double")


def _excess(value: Column, mean: Column, sd: Column) -> Column:
    z = F.when(F.coalesce(sd, F.lit(0.0)) < 1e-12, F.lit(0.0)).otherwise((value - mean) / F.when(F.coalesce(sd, F.lit(0.0)) < 1e-12, F.lit(1.0)).otherwise(sd))
    return F.pow(F.greatest(z, F.lit(0.0)), F.lit(2.0))


def penalty(subs: DataFrame, ref: str = "siblings", features: tuple[str, ...] = ("len", "ent"), lam: float = LAMBDA, samples: DataFrame | None = None) -> DataFrame:
    """Adds l_struct (squared excess over the reference, summed) and penalty_factor = exp(-lam * l_struct).

    ref: 'siblings' (population-weighted moments over the parent's children), 'leave_one_out' (the same without the
    child), 'global' (over all children), 'samples' (length moments over the parent's rows: ``samples`` with k,
    n_tokens; entropy as for siblings).  Below the reference is free; a reference without spread gives 0.
    """
    w = Window.partitionBy(*([] if ref == "global" else ["k"]))
    n = F.col("n").cast("double")
    out, total = subs, F.lit(0.0)
    if ref == "samples":
        moments = samples.groupBy("k").agg(F.avg(F.log1p("n_tokens")).alias("__m_len"), F.stddev_pop(F.log1p("n_tokens")).alias("__s_len"))
        out = out.join(F.broadcast(moments), "k")
    for f in features:
        x = F.col(f"z_{f}")
        if ref == "samples" and f == "len":
            total = total + _excess(x, F.col("__m_len"), F.col("__s_len"))
            continue
        s0, s1, s2 = F.sum(n).over(w), F.sum(n * x).over(w), F.sum(n * x * x).over(w)
        if ref == "leave_one_out":
            s0, s1, s2 = s0 - n, s1 - n * x, s2 - n * x * x
            s0 = F.nullif(s0, F.lit(0.0))
        out = out.withColumns({f"__m_{f}": F.coalesce(s1 / s0, x), f"__v_{f}": F.coalesce(s2 / s0 - F.pow(s1 / s0, F.lit(2.0)), F.lit(0.0))})
        total = total + _excess(x, F.col(f"__m_{f}"), F.sqrt(F.greatest(F.col(f"__v_{f}"), F.lit(0.0))))
    out = out.withColumn("l_struct", total).withColumn("penalty_factor", F.exp(-F.lit(lam) * F.col("l_struct")))
    return out.drop(*[c for c in out.columns if c.startswith("__")])


def gate(subs: DataFrame, parents: DataFrame | None) -> DataFrame:
    """Adds beta, the logistic of a child's cohesion less its parent's (one-row ``parents`` without k: the corpus's).

    A child of one row takes its parent's cohesion: exactly one half.
    """
    ref = parents.select(*(["k"] if "k" in parents.columns else []), F.col("z_coh").alias("__coh"))
    out = subs.join(F.broadcast(ref), "k") if "k" in ref.columns else subs.crossJoin(F.broadcast(ref))
    return out.withColumn("beta", F.when(F.col("n") == 1, F.lit(0.5)).otherwise(1 / (1 + F.exp(F.col("__coh") - F.col("z_coh"))))).drop("__coh")


def weight(subs: DataFrame, eps: float = EPSILON, normalise: str = "global") -> DataFrame:
    """Adds w from r, p, penalty_factor and beta; w sums to one over all rows, or to r within each parent.

    If no sub-cluster has a semantic score above 0, the two geometric factors decide.
    """
    any_p = subs.agg(F.max(F.coalesce("p", F.lit(0.0))).alias("__top"))
    out = subs.crossJoin(F.broadcast(any_p))
    p = F.when(F.col("__top") > 0, F.coalesce("p", F.lit(0.0))).otherwise(F.lit(1.0))
    out = out.withColumn("__raw", F.col("r") * p * F.col("penalty_factor") * (F.col("beta") + F.lit(eps)))
    if normalise == "global":
        out = out.crossJoin(F.broadcast(out.agg(F.sum("__raw").alias("__all"))))
        return out.withColumn("w", F.col("__raw") / F.col("__all")).drop("__raw", "__all", "__top")
    w = Window.partitionBy("k")
    return out.withColumn("w", F.col("r") * F.coalesce(F.col("__raw") / F.nullif(F.sum("__raw").over(w), F.lit(0.0)), F.col("n") / F.sum("n").over(w))).drop("__raw", "__top")
