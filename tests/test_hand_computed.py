"""Small fixtures with known answers."""

from __future__ import annotations

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from curator.functions.keyed import key32
from curator.operators import consensus, lloyd, measures, mixing, refine, resolution, sampling, theory
from curator.operators.features import cluster_features, znorm


def test_keyed_number(spark):
    row = spark.range(1).select(F.conv(F.substring(F.md5(F.lit("a").cast("binary")), 1, 8), 16, 10).cast("long").alias("x"), key32("id").alias("y")).first()
    assert row["x"] == 214005177 and 0 <= row["y"] < 2**32


def test_entropy_and_features(spark):
    rows = [(0, lang, 10, 0.5) for lang in "aabc"]
    f = cluster_features(spark.createDataFrame(rows, "k int, lang string, n_tokens long, dist double"), ["k"]).first()
    assert f["z_ent"] == pytest.approx(1.5 * math.log(2))
    assert f["z_coh"] == pytest.approx(1 / 0.501) and f["z_size"] == pytest.approx(math.log(5)) and f["z_len"] == pytest.approx(math.log(11))


def test_constant_feature_is_zero(spark):
    z = znorm(spark.createDataFrame([(k, 1.0, 2.0, 3.0, float(k)) for k in range(3)], "k int, z_coh double, z_size double, z_len double, z_ent double")).collect()
    assert all(r["zn_coh"] == 0 for r in z) and sum(r["zn_ent"] for r in z) == pytest.approx(0)
    w = consensus.weights(znorm(spark.createDataFrame([(k, 1.0, 2.0, 3.0, float(k)) for k in range(3)], "k int, z_coh double, z_size double, z_len double, z_ent double")))
    assert sum(w.values()) == pytest.approx(1)


def test_softmax(spark):
    even = mixing.budget(spark.createDataFrame([(k, 1.0) for k in range(4)], "k int, s double")).collect()
    assert [r["r"] for r in even] == pytest.approx([0.25] * 4)
    two = {r["k"]: r["r"] for r in mixing.budget(spark.createDataFrame([(0, 0.0), (1, math.log(3))], "k int, s double")).collect()}
    assert two == pytest.approx({0: 0.25, 1: 0.75})


@pytest.mark.parametrize("x, y, want", [((1, 2, 3), (1, 2, 3), 1), ((1, 2, 3), (3, 2, 1), -1), ((1, 2, 3), (1, 3, 2), 1 / 3), ((1, 1, 2), (1, 2, 3), 2 / math.sqrt(6))])
def test_tau(spark, x, y, want):
    assert resolution.tau_value(np.array(x, float), np.array(y, float)) == pytest.approx(want)
    df = spark.createDataFrame([(i, float(a), float(b)) for i, (a, b) in enumerate(zip(x, y, strict=True))], "i int, s double, s_hat double")
    assert resolution.tau(df).first()[0] == pytest.approx(want)


def test_tau_undefined():
    assert resolution.tau_value(np.array([1.0]), np.array([1.0])) is None
    assert resolution.tau_value(np.array([1.0, 1.0]), np.array([1.0, 2.0])) is None


def test_bridge(spark):
    e = [[1.0] + [0.0] * 63, [0.0, 1.0] + [0.0] * 62]
    c = spark.createDataFrame([(i, v) for i, v in enumerate(e)], "i int, mu array<double>")
    pi = {(r["i"], r["j"]): r["pi"] for r in resolution.bridge(c, c.withColumnRenamed("i", "j")).collect()}
    assert pi[0, 0] == pytest.approx(1 / (1 + math.exp(-20)))
    flat = resolution.bridge(c, c.withColumnRenamed("i", "j"), 0.0).collect()
    assert all(r["pi"] == pytest.approx(0.5) for r in flat)


def test_gate_and_weight(spark):
    subs = spark.createDataFrame([(0, 0, 5, 1.0, 2.0, 1.0), (0, 1, 5, 1.0 + math.log(3), 2.0, 1.0), (0, 2, 1, 9.0, 2.0, 1.0)], "k int, j int, n long, z_coh double, z_len double, z_ent double")
    g = {r["j"]: r["beta"] for r in refine.gate(subs, spark.createDataFrame([(0, 1.0)], "k int, z_coh double")).collect()}
    assert g == pytest.approx({0: 0.5, 1: 0.75, 2: 0.5})
    w = refine.weight(spark.createDataFrame([(0, 0, 0.5, 0.8, 1.0, 0.5, 3), (0, 1, 0.5, 0.4, 1.0, 0.5, 3)], "k int, j int, r double, p double, penalty_factor double, beta double, n long")).orderBy("j").collect()
    assert [r["w"] for r in w] == pytest.approx([2 / 3, 1 / 3])
    zero = refine.weight(spark.createDataFrame([(0, 0, 0.5, 0.0, 1.0, 0.5, 3), (0, 1, 0.5, 0.0, 0.5, 0.5, 3)], "k int, j int, r double, p double, penalty_factor double, beta double, n long"))
    assert zero.agg(F.sum("w")).first()[0] == pytest.approx(1)


def test_penalty(spark):
    rows = [(0, j, 1, float(x), 1.0) for j, x in enumerate([0, 0, 0, 0, 5])]
    df = spark.createDataFrame(rows, "k int, j int, n long, z_len double, z_ent double")
    got = {r["j"]: (r["l_struct"], r["penalty_factor"]) for r in refine.penalty(df).collect()}
    assert got[0] == (0.0, 1.0) and got[4][0] == pytest.approx(4.0) and got[4][1] == pytest.approx(math.exp(-2))
    assert all(r["penalty_factor"] == 1 for r in refine.penalty(df, lam=0.0).collect())


def test_sub_counts(spark):
    m = refine.sub_counts(spark.createDataFrame([(0, 1), (1, 10), (2, 100)], "k int, n long")).orderBy("k").collect()
    assert [r["m"] for r in m] == [1, 4, 10]


def test_water_filling(spark):
    q = sampling.quotas(spark.createDataFrame([(0, 0.5, 10), (1, 0.25, 100), (2, 0.25, 100)], "k int, w double, supply long"), 60).orderBy("k").collect()
    assert [r["quota"] for r in q] == pytest.approx([10, 25, 25])
    everything = sampling.quotas(spark.createDataFrame([(0, 0.5, 10)], "k int, w double, supply long"), 60).first()
    assert everything["quota"] == 10


def test_bound_on_a_line(spark):
    assigned = spark.createDataFrame([(0, 0, 1.0), (1, 0, 1.0)], "doc_id long, k int, dist double")
    g = theory.gain(assigned, spark.createDataFrame([(1,)], "doc_id long"))
    assert theory.bound(g).first()["bound"] == pytest.approx(4) and g.first()["gain"] == pytest.approx(0)
    assert theory.w2_exact(np.array([[-1.0], [1.0]]), np.array([0.5, 0.5]), np.array([[1.0]]), np.array([1.0])) == pytest.approx(2)
    none = theory.pruning(theory.gain(assigned, spark.createDataFrame([], "doc_id long"))).first()[0]
    assert none is None


def test_bound_holds_for_random_subsets():
    rng = np.random.default_rng(1)
    for _ in range(5):
        x = rng.normal(size=(24, 3))
        k = rng.integers(0, 3, 24)
        chosen = np.concatenate([np.flatnonzero(k == c)[: rng.integers(1, 4)] for c in range(3)])
        mu = np.array([x[k == c].mean(0) for c in range(3)])
        alpha = np.array([(k == c).mean() for c in range(3)])
        b = np.array([alpha[k[i]] / (k[chosen] == k[i]).sum() for i in chosen])
        exact = theory.w2_exact(x, np.full(24, 1 / 24), x[chosen], b)
        d2 = ((x - mu[k]) ** 2).sum(1)
        bound = 2 * d2.mean() + 2 * (b * d2[chosen]).sum()
        assert exact <= bound + 1e-9


def test_efficiency():
    assert measures.efficiency([(0.5, 1), (1, 2)], [(0.5, 2), (1, 3)]) == pytest.approx(2)
    assert measures.efficiency([(0.5, 1), (1, 2)], [(0.5, 1), (1, 1.5)]) is None


def test_published_averages():
    for _, _, _, printed, values in measures.PUBLISHED:
        assert abs(sum(values) / 7 - printed) <= 0.05


def test_lloyd_equals_numpy(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(200, 8))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "doc_id long, emb array<double>").repartition(3)
    start = lloyd.seed_rows(df, 5)
    mu = start.copy()
    for _ in range(3):
        k = np.argmax(np.round(x @ mu.T, 12), axis=1)
        for c in range(5):
            if (k == c).any():
                v = x[k == c].mean(0)
                mu[c] = v / np.linalg.norm(v)
    assert np.allclose(lloyd.sweep(df, [5], iters=3, tol=-1)[5], mu)
    got = {r["doc_id"]: r["k"] for r in lloyd.assign(df, mu).collect()}
    want = np.argmax(np.round(x @ mu.T, 12), axis=1)
    assert all(got[i] == want[i] for i in range(200))


def test_near_copies_decided_on_whole_sets(spark):
    from curator.operators import hygiene

    words = [f"w{i}" for i in range(200)]
    edited = [f"e{i}" if i % 33 == 16 else w for i, w in enumerate(words)]
    copy = [*words[:-1], "end"]
    rows = [(1, " ".join(words)), (2, " ".join(edited)), (3, " ".join(copy))]
    # 196 grams each: 1 and 2 share 166 (0.73 of the union), 1 and 3 share 195
    kept = hygiene.dedup_near(spark.createDataFrame(rows, "doc_id long, text string")).select("doc_id").collect()
    assert sorted(r[0] for r in kept) == [1, 2]
