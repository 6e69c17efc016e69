"""The whole method on planted clusters, and the registry."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from curator.operators import sampling
from curator.plans import curation
from curator.plans.curation import CurationPlan


@pytest.fixture(scope="module")
def planted(spark):
    rng = np.random.default_rng(5)
    rows, i = [], 0
    for c in range(6):
        centre = np.zeros(16)
        centre[c] = 1
        for _ in range(80):
            v = centre + rng.normal(size=16) * (0.05 if c else 0.35)
            rows.append((i, "ab"[int(rng.integers(0, 2))] if c == 1 else "a", f"s{i % 3}", int(rng.integers(50, 100)) if c != 2 else 1000, (v / np.linalg.norm(v)).tolist()))
            i += 1
    return spark.createDataFrame(rows, "doc_id long, lang string, source string, n_tokens long, emb array<double>").persist()


def test_curate(spark, planted):
    plan = CurationPlan(k=6, probe_fraction=1.0, scorer="none", budget=sampling.Budget(fraction=0.3))
    got = curation.curate(planted, plan)
    assert got.weights.agg(F.sum("w")).first()[0] == pytest.approx(1)
    n = got.subset.count()
    assert 0 < n < planted.count()
    again = curation.curate(planted.repartition(5), plan).subset
    assert {r[0] for r in again.select("doc_id").collect()} == {r[0] for r in got.subset.select("doc_id").collect()}
    half = sampling.epoch_prefix(got.subset, 0.5)
    assert half.join(got.subset.select("doc_id"), "doc_id", "left_anti").count() == 0
    # documents, too, can be what the budget is spent in
    some = curation.draw_subset(got.sub, got.weights, CurationPlan(sampler="exact", budget=sampling.Budget(docs=100)))
    assert 60 <= some.count() <= 100


def test_loose_mixed_and_long_cells_get_least(spark, planted):
    from curator.functions.vectors import centres, with_distance
    from curator.operators import consensus, mixing
    from curator.operators.features import cluster_features, znorm

    cells = planted.withColumn("k", (F.col("doc_id") / 80).cast("int"))
    z = znorm(cluster_features(with_distance(cells, centres(cells, ["k"], 16), ["k"], "dist", 16), ["k"]))
    share = {r["k"]: r["r"] for r in mixing.budget(mixing.score(z, consensus.weights(z))).collect()}
    assert max(share[c] for c in (0, 1, 2)) < min(share[c] for c in (3, 4, 5))


def test_search_and_ablations(spark, planted):
    plan = CurationPlan(k=None, grid=(4, 6), stride=2, probe_fraction=1.0, iters=5, scorer="none")
    curve, _ = curation.search(planted, plan)
    assert [k for k, _ in curve] == [4, 6]
    fixed = CurationPlan(k=4, probe_fraction=1.0, iters=4, scorer="none")
    for result in (curation.no_macro(planted, fixed), curation.no_micro(planted, fixed), curation.flat_random(planted, fixed, 12), curation.flat_scored(planted, fixed, 12)):
        assert result.subset.count() > 0


def test_registry():
    import __spark_entry__ as entry

    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_entry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0


def test_centroid_joins_are_broadcast(spark, sf):
    from curator.functions.vectors import centres, with_distance
    from curator.sources.tables import corpus_vec

    c = corpus_vec(spark, sf)
    plan = with_distance(c, centres(c, ["k"]), ["k"])._jdf.queryExecution().toString()
    assert "BroadcastHashJoin" in plan


def test_seed_spread(spark, sf):
    from curator.plans.workloads import seed_spread

    got = {(r["method"], r["metric"], r["lang"]): r["value"] for r in seed_spread(spark, sf, seeds=2, methods=("random", "mixture optimiser"), plan=CurationPlan(k=8)).collect()}
    assert {m for m, _, _ in got} == {"random", "mixture optimiser"}
    for (method, metric, lang), value in got.items():
        if metric.endswith("_mean"):
            stem = metric.removesuffix("_mean")
            least, most = got[method, f"{stem}_least", lang], got[method, f"{stem}_most", lang]
            assert value is None or least - 1e-9 <= value <= most + 1e-9


def test_seeds_share_what_no_seed_changes(spark, sf, monkeypatch):
    from curator.operators import baselines, measures
    from curator.plans.workloads import seed_spread

    calls = {"domain_counts": 0, "cross_entropies": 0}
    for owner, name in ((baselines, "domain_counts"), (measures, "cross_entropies")):
        f = getattr(owner, name, None)

        def counted(*a, _f=f, _name=name, **k):
            calls[_name] += 1
            return _f(*a, **k)

        monkeypatch.setattr(owner, name, counted)
    assert seed_spread(spark, sf, seeds=2, methods=("random", "mixture optimiser"), plan=CurationPlan(k=8)).count() > 0
    # the corpus and the held-out texts once each, and one scan that measures the subsets of both seeds
    assert calls == {"domain_counts": 2, "cross_entropies": 1}


def test_bridge_scales_share_the_fitted_resolutions(spark, sf, monkeypatch):
    from curator.operators import lloyd
    from curator.plans.workloads import Lab, hyper

    sweeps, f = [], lloyd.sweep
    monkeypatch.setattr(lloyd, "sweep", lambda probe, sizes, *a, **k: sweeps.append(list(sizes)) or f(probe, sizes, *a, **k))
    monkeypatch.setattr("curator.plans.workloads.Lab", lambda spark, d: Lab(spark, d, CurationPlan(grid=(4, 6), stride=2, iters=3)))
    got = [r for r in hyper(spark, sf).collect() if r["method"].startswith("scale")]
    assert sweeps == [[4, 6, 8]] and len({r["method"] for r in got}) == 4


def test_ablations_share_their_clusters(spark, sf, monkeypatch):
    from curator.operators import refine
    from curator.plans.workloads import ABLATIONS, Lab

    lab, made, f = Lab(spark, sf, CurationPlan(k=8, iters=3)), [], refine.subcluster
    monkeypatch.setattr(refine, "subcluster", lambda rows, counts, **k: made.append(counts.count()) or f(rows, counts, **k))
    got = {m: {r[0] for r in lab.subset(m).collect()} for m in ABLATIONS}
    # the sub-clusters of all clusters once, and the flat clusters once
    assert sorted(made) == [1, 8]
    # each method by itself draws the same subset
    alone = {"no macro": curation.no_macro(lab.store, lab.plan, lab.docs, lab.labels), "flat scored": curation.flat_scored(lab.store, lab.plan, lab.k_total(), lab.docs, lab.labels)}
    assert all({r["doc_id"] for r in result.subset.collect()} == got[m] for m, result in alone.items())


def test_decontamination_searches_the_texts_once(spark, sf, monkeypatch):
    from curator.operators import hygiene
    from curator.plans import workloads

    calls, contains = [], hygiene.contains
    monkeypatch.setattr(hygiene, "contains", lambda *a, **b: calls.append(a) or contains(*a, **b))
    got = {r["method"]: r["value"] for r in workloads.decontaminate(spark, sf).collect()}
    docs, bench = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "benchmark"))
    kept, audit = hygiene.decontaminate(docs, bench)
    items = [r["text"] for r in bench.collect()]
    count = lambda df: sum(any(i in r["text"] for i in items) for r in df.where("text IS NOT NULL").collect())
    assert got == {"before": count(docs), "after": count(kept), "ngram": audit.select("doc_id").distinct().count()}
    assert len(calls) == 1


def test_curves_of_several_subsets_out_of_one_scan(spark, sf):
    from curator.operators import measures

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    held, parts = docs.where("doc_id % 5 = 0"), (0.1, 0.5, 1.0)
    subsets = [docs.where("doc_id % 5 = 1").select("doc_id"), docs.where("doc_id % 5 > 0").select("doc_id"), docs.where("doc_id < 0").select("doc_id")]
    got = {(r["i"], r["part"], r["lang"]): r["value"] for r in measures.cross_entropy_curves(docs, measures.members(subsets), 3, held, parts).collect()}
    want = {(i, r["part"], r["lang"]): r["value"] for i, s in enumerate(subsets) for r in measures.cross_entropy_at(docs.join(s, "doc_id", "left_semi"), held, parts).collect()}
    assert got == pytest.approx(want) and len(got) == len(want) > 9


def test_groups_are_measured_in_one_scan(spark, sf, monkeypatch):
    from curator.operators import measures
    from curator.plans import workloads

    calls, many = [], measures.cross_entropies
    monkeypatch.setattr(measures, "cross_entropies", lambda *a, **b: calls.append(a) or many(*a, **b))
    monkeypatch.setattr(workloads.Lab, "subset", lambda self, method: self.docs.where(f"doc_id % 2 = {int(method == 'random')}").select("doc_id"))
    got = {(r["method"], r["lang"]): r["value"] for r in workloads.suite_groups(spark, sf).where("workload = 'groups'").collect()}
    lab = workloads.Lab(spark, sf)
    held = lab.held_out.withColumn("lang", F.when(workloads.n_tokens("text") < 200, "short").otherwise("long"))
    want = {(m, r["lang"]): r["value"] for m in ("random", "curator") for r in measures.cross_entropy(lab.docs.join(lab.subset(m), "doc_id", "left_semi"), held).collect()}
    assert got == pytest.approx(want) and len(calls) == 1


def test_blend_needs_no_vectors(spark, sf, monkeypatch):
    from curator.operators import embed
    from curator.plans import workloads

    lab = workloads.Lab(spark, sf)
    assert sorted(lab.lengths.collect()) == sorted(lab.store.select("doc_id", "n_tokens").collect())
    monkeypatch.setattr(embed, "hashed_text", None)
    assert {r["method"] for r in workloads.blend(spark, sf).collect()} == {"curated", "frozen"}


def test_shapes_are_measured_on_written_tables(spark, sf, monkeypatch):
    from types import SimpleNamespace

    from curator.operators import measures
    from curator.plans import workloads

    plans, ks = [], measures.ks_normal
    monkeypatch.setattr(measures, "ks_normal", lambda df, n: plans.append(df._jdf.queryExecution().optimizedPlan().toString()) or ks(df, n))
    sub = spark.createDataFrame([(i % 3, i % 5, i / 7, i) for i in range(60)], "k int, j int, dist_sub double, n_tokens long")
    monkeypatch.setattr(workloads.Lab, "full", lambda self: SimpleNamespace(sub=sub))
    assert workloads.feature_shape(spark, sf).count() == 28
    assert len(plans) == 8 and not any("regexp" in p or "Aggregate" in p for p in plans)
