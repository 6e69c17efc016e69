"""One plan object behind the curator, its ablations and the baselines, so that only the choice of samples differs."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from curator.functions.keyed import SEED
from curator.functions.text import n_tokens
from curator.functions.vectors import centres as group_centres
from curator.functions.workspace import release, stash
from curator.operators import baselines, consensus, embed, hygiene, lloyd, mixing, probes, refine, resolution, sampling
from curator.operators.features import FEATURES, cluster_features, znorm


@dataclass(frozen=True)
class CurationPlan:
    """Parameters; the defaults are the published ones where there are any."""

    k: int | None = None  # None: searched over ``grid``
    grid: tuple[int, ...] = tuple(range(8, 97, 8))
    stride: int = 8
    rule: str = "argmax"
    tau_variant: str = "b"
    repeats: int = 1
    probe_fraction: float = 0.2
    probe_cap: int | None = None
    iters: int = 10
    scale: float = 20.0
    weights: str = "spectral"
    affinity: str = "shifted"
    temperature: float = 1.0
    sub_c: float = 1.0
    sub_cap: int | None = None
    probes: int = 3
    scorer: str = "labels"  # labels, heuristic, none
    lam: float = 0.5
    eps: float = 0.01
    gate: bool = True
    ref: str = "siblings"
    normalise: str = "global"
    budget: sampling.Budget = field(default_factory=lambda: sampling.Budget(fraction=0.3))
    per: str = "tokens"  # what a budget given as a fraction is spent in: tokens or docs
    max_repeat: float = 1.0
    sampler: str = "threshold"
    seed: int = SEED


@dataclass
class CurationResult:
    subset: DataFrame
    curve: list[tuple[int, float | None]] = field(default_factory=list)
    k: int | None = None
    budget: DataFrame | None = None
    weights: DataFrame | None = None
    assigned: DataFrame | None = None
    sub: DataFrame | None = None


def cleaned(docs: DataFrame, bench: DataFrame | None = None, near: bool = False) -> DataFrame:
    """documents -> the same with n_tokens: benchmark items and copies gone."""
    if bench is not None:
        docs, _ = hygiene.decontaminate(docs, bench)
    docs = hygiene.dedup_near(hygiene.dedup_exact(docs)) if near else hygiene.dedup_exact(docs)
    return docs.withColumn("n_tokens", n_tokens("text"))


def front_end(docs: DataFrame, bench: DataFrame | None = None, d: int = 64, near: bool = False) -> DataFrame:
    """documents -> feature store (doc_id, lang, source, n_tokens, emb): benchmark items and copies gone first.

    The store is written once; texts are not read again but for probes and results.
    """
    docs = cleaned(docs, bench, near)
    return stash(embed.hashed_text(docs, d, keep=("doc_id", "lang", "source", "n_tokens")), "features")


def _scored(assigned: DataFrame, how: str, kind: str) -> tuple[DataFrame, dict[str, float]]:
    z = stash(znorm(cluster_features(assigned, ["k"])), "clusters")
    w = consensus.weights(z, how, kind)
    return mixing.score(z, w), w


Resolutions = list[tuple[dict[int, np.ndarray], dict[int, np.ndarray]]]


def resolutions(store: DataFrame, plan: CurationPlan) -> Resolutions:
    """(centres, scores) of every K of the grid and every K + stride, once for each repeat.

    A repeat fits all K in shared scans and describes all their clusters in one more; a row per cluster reaches the driver.
    """
    probe = stash(lloyd.probe_sample(store, plan.probe_fraction, plan.seed, plan.probe_cap), "probe")
    sizes = sorted(set(plan.grid) | {k + plan.stride for k in plan.grid})
    out: Resolutions = []
    for r in range(plan.repeats):
        mus = lloyd.sweep(probe, sizes, plan.iters, seed=plan.seed + r)
        rows = cluster_features(lloyd.assign_all(probe, mus, keep=("lang", "n_tokens")), ["resolution", "k"]).collect() if mus else []
        out.append((mus, {size: _scores_of([row for row in rows if row["resolution"] == size], len(mu), plan) for size, mu in mus.items()}))
    release(probe)
    return out


def stability(store: DataFrame, plan: CurationPlan, scales: tuple[float, ...] | None = None, given: Resolutions | None = None) -> tuple[dict[float, dict[int, list[float]]], dict[int, np.ndarray]]:
    """For each bridge scale, the stability values of every K of the grid against K + stride (one for each repeat), and the
    centres of the first repeat.  ``given``: what :func:`resolutions` made of the same store and plan.
    """
    scales = scales or (plan.scale,)
    values: dict[float, dict[int, list[float]]] = {c: {k: [] for k in plan.grid} for c in scales}
    given = resolutions(store, plan) if given is None else given
    for mus, scores in given:
        for k in plan.grid:
            fine = k + plan.stride
            if k not in scores or fine not in scores:
                continue
            a, b = ~np.isnan(scores[k]), ~np.isnan(scores[fine])
            cosine = mus[k][a] @ mus[fine][b].T
            for c in scales:
                pi = np.exp(c * (cosine - cosine.max(1, keepdims=True)))
                pi /= pi.sum(1, keepdims=True)
                j = resolution.tau_value(scores[k][a], pi @ scores[fine][b], plan.tau_variant)
                if j is not None:
                    values[c][k].append(j)
    return values, next((mus for mus, _ in given if mus), {})


def _scores_of(rows: list, k: int, plan: CurationPlan) -> np.ndarray:
    """Geometric scores of the clusters of one resolution; nan for a cluster without samples."""
    out = np.full(k, np.nan)
    at = [row["k"] for row in rows]
    x = {f: np.array([row[f"z_{f}"] for row in rows]) for f in FEATURES}
    zn = {f: (v - v.mean()) / v.std() if v.std() >= 1e-12 else np.zeros(len(v)) for f, v in x.items()}
    w = consensus.weights_of(zn, plan.weights, plan.affinity)
    out[at] = sum(consensus.SIGNS[f] * w[f] * zn[f] for f in FEATURES)
    return out


def search(store: DataFrame, plan: CurationPlan, given: Resolutions | None = None) -> tuple[list[tuple[int, float | None]], dict[int, np.ndarray]]:
    """Stability of every K of the grid against K + stride (averaged over seeds), and the centres of the first seed."""
    values, first = stability(store, plan, given=given)
    return [(k, float(np.mean(v)) if v else None) for k, v in values[plan.scale].items()], first


Macro = tuple[DataFrame, DataFrame, list, int]


def macro(store: DataFrame, plan: CurationPlan, given: Resolutions | None = None) -> Macro:
    """(assigned, budget with s and r, curve, K): clusters for all samples and each cluster's share.

    ``given``: what :func:`resolutions` made of the same store and plan, if K is searched.
    """
    curve: list = []
    if plan.k is None:
        curve, mus = search(store, plan, given)
        k = resolution.choose(curve, plan.rule) or min(plan.grid)
    else:
        k, mus = plan.k, lloyd.sweep(lloyd.probe_sample(store, plan.probe_fraction, plan.seed, plan.probe_cap), [plan.k], plan.iters, seed=plan.seed)
    mu = mus.get(k)
    if mu is None:  # fewer probes than clusters
        k = min(k, store.count())
        mu = lloyd.fit(store, k, plan.iters, seed=plan.seed)
    assigned = stash(lloyd.assign(store, mu, keep=("lang", "source", "n_tokens", "emb")), "assigned")
    scored, _ = _scored(assigned, plan.weights, plan.affinity)
    return assigned, stash(mixing.budget(scored, plan.temperature), "budget"), curve, k


def semantic(sub: DataFrame, plan: CurationPlan, docs: DataFrame | None, labels: DataFrame | None) -> DataFrame:
    """(k, j, p) of every sub-cluster."""
    chosen = probes.select(sub, plan.probes)
    if plan.scorer == "labels" and labels is not None:
        return probes.score_labels(chosen, labels)
    if plan.scorer == "heuristic" and docs is not None:
        return probes.score_heuristic(chosen, docs)
    return sub.select("k", "j").distinct().withColumn("p", F.lit(1.0))


def micro(assigned: DataFrame, budget: DataFrame, plan: CurationPlan, docs: DataFrame | None = None, labels: DataFrame | None = None, reference: str = "parent", given: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """(sub, weights): sub-clusters of every cluster and their weights.

    reference 'global' takes penalty and gate against the whole corpus, as the ablations without a hierarchy do.
    ``given``: the sub-clusters of the same samples, cluster sizes and plan; the clusters' shares don't change them.
    """
    sub = given
    if sub is None:
        counts = stash(refine.sub_counts(budget.select("k", "n"), plan.sub_c, plan.sub_cap), "counts")
        sub = stash(refine.subcluster(assigned, counts, iters=plan.iters, seed=plan.seed), "sub")
    child = cluster_features(sub, ["k", "j"], "dist_sub")
    parent = cluster_features(sub, ["k"], "dist") if reference == "parent" else _corpus_features(sub)
    w = refine.penalty(child, "global" if reference == "global" else plan.ref, lam=plan.lam)
    w = refine.gate(w, parent) if plan.gate else w.withColumn("beta", F.lit(1.0))
    w = w.join(F.broadcast(budget.select("k", "r")), "k").join(semantic(sub, plan, docs, labels), ["k", "j"], "left")
    return sub, _weighted(w, plan.eps, plan.normalise)


def _weighted(factors: DataFrame, eps: float, normalise: str = "global") -> DataFrame:
    """Weights of the sub-clusters, written.  Their factors are written before, as the weights read them four times."""
    factors = stash(factors, "factors")
    out = stash(refine.weight(factors, eps, normalise), "weights")
    release(factors)
    return out


def _corpus_features(rows: DataFrame) -> DataFrame:
    """One row: features of the corpus as one cluster, around its own centre."""
    one = rows.withColumn("__all", F.lit(0))
    mu = group_centres(one, ["__all"], len(rows.select("emb").first()[0]))
    from curator.functions.vectors import with_distance

    return cluster_features(with_distance(one.drop("dist"), mu, ["__all"], "dist", len(rows.select("emb").first()[0])), [], "dist")


def draw_subset(rows: DataFrame, weights: DataFrame, plan: CurationPlan, keys: tuple[str, ...] = ("k", "j")) -> DataFrame:
    """Rows drawn under the plan's budget: weights are shares of tokens, or of documents."""
    unit = plan.budget.unit(plan.per)
    supply = rows.groupBy(*keys).agg((F.sum("n_tokens") if unit == "tokens" else F.count(F.lit(1))).alias("supply"))
    cells = stash(weights.select(*keys, "w").join(supply, list(keys)), "cells")
    volume = plan.budget.volume(cells.agg(F.coalesce(F.sum("supply"), F.lit(0))).first()[0])
    quota = sampling.quotas(cells, volume, plan.max_repeat)
    if plan.sampler == "exact":
        return sampling.take_exact(rows, quota, plan.seed, keys, "n_tokens" if unit == "tokens" else None)
    take = {"threshold": sampling.take_threshold, "repeat": sampling.take_repeat}[plan.sampler]
    return take(rows, quota, plan.seed, keys)


def curate(store: DataFrame, plan: CurationPlan, docs: DataFrame | None = None, labels: DataFrame | None = None, given: Macro | None = None) -> CurationResult:
    """Feature store -> subset with every table behind it.  ``given``: what :func:`macro` made of the same store and plan."""
    assigned, budget, curve, k = given or macro(store, plan)
    sub, weights = micro(assigned, budget, plan, docs, labels)
    return CurationResult(draw_subset(sub, weights, plan).drop("emb"), curve, k, budget, weights, assigned, sub)


def no_macro(store: DataFrame, plan: CurationPlan, docs: DataFrame | None = None, labels: DataFrame | None = None, given: Macro | None = None, sub: DataFrame | None = None) -> CurationResult:
    """Uniform shares; penalty and gate refer to the whole corpus.  ``sub``: what :func:`curate` made of the same store and plan."""
    assigned, budget, curve, k = given or macro(store, plan)
    even = stash(mixing.uniform(budget.drop("r")), "even")
    sub, weights = micro(assigned, even, plan, docs, labels, "global", sub)
    return CurationResult(draw_subset(sub, weights, plan).drop("emb"), curve, k, even, weights, assigned, sub)


def no_micro(store: DataFrame, plan: CurationPlan, given: Macro | None = None) -> CurationResult:
    """Learned shares, uniform within each cluster."""
    assigned, budget, curve, k = given or macro(store, plan)
    subset = draw_subset(assigned, budget.withColumnRenamed("r", "w"), plan, ("k",)).drop("emb")
    return CurationResult(subset, curve, k, budget, None, assigned)


def flat_clusters(store: DataFrame, plan: CurationPlan, k_total: int) -> DataFrame:
    """One flat clustering with as many clusters as the hierarchy has sub-clusters.

    The corpus is one parent whose sub-clusters are fitted and met in salted parts, so neither samples nor centres reach
    the driver, however many there are.
    """
    n = store.count()
    one = store.select("doc_id", "lang", "source", "n_tokens", "emb", F.lit(0).alias("k"))
    counts = store.sparkSession.createDataFrame([(0, n, min(k_total, n))], "k int, n long, m int")
    flat = refine.subcluster(one, counts, iters=plan.iters, seed=plan.seed).drop("k")
    return stash(flat.withColumnsRenamed({"j": "k", "dist_sub": "dist"}), "flat")


def flat_random(store: DataFrame, plan: CurationPlan, k_total: int, flat: DataFrame | None = None) -> CurationResult:
    """Flat clusters, the same sampling ratio in each.  ``flat``: what :func:`flat_clusters` made of the same arguments."""
    flat = flat_clusters(store, plan, k_total) if flat is None else flat
    cells = flat.groupBy("k").agg(F.sum("n_tokens").alias("w"))
    return CurationResult(draw_subset(flat, cells.withColumn("w", F.col("w").cast("double")), plan, ("k",)).drop("emb"), k=k_total, assigned=flat)


def flat_scored(store: DataFrame, plan: CurationPlan, k_total: int, docs: DataFrame | None = None, labels: DataFrame | None = None, flat: DataFrame | None = None) -> CurationResult:
    """Flat clusters weighted by semantic score, penalty and gate with the whole corpus as the parent.  ``flat``: as there."""
    flat = flat_clusters(store, plan, k_total) if flat is None else flat
    sub = flat.withColumns({"j": F.col("k"), "dist_sub": F.col("dist"), "k": F.lit(0)})
    child = cluster_features(sub, ["k", "j"], "dist_sub")
    w = refine.gate(refine.penalty(child, "global", lam=plan.lam), _corpus_features(sub))
    w = w.withColumn("r", F.lit(1.0)).join(semantic(sub, plan, docs, labels), ["k", "j"], "left")
    weights = _weighted(w, plan.eps)
    return CurationResult(draw_subset(sub, weights, plan).drop("emb"), k=k_total, weights=weights, assigned=flat, sub=sub)


def blend(curated: DataFrame, frozen: DataFrame, tokens: float, ratio: tuple[float, float] = (7, 3), seed: int = SEED) -> DataFrame:
    """Both frames (doc_id, n_tokens, ...) cut to their share of a token budget, with ``component``; the frozen draw
    depends on its own ids only, so it is the same for every curated set."""
    out = None
    for name, df, share in (("curated", curated, ratio[0]), ("frozen", frozen, ratio[1])):
        have = df.agg(F.coalesce(F.sum("n_tokens"), F.lit(0))).first()[0]
        want = tokens * share / sum(ratio)
        part = baselines.random(df, min(1.0, want / have) if have else 0.0, seed + 11).select("doc_id", "n_tokens", F.lit(name).alias("component"))
        out = part if out is None else out.unionByName(part)
    return out
