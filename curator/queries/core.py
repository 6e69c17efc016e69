"""Method cores on the corpus with given vectors, each with the DuckDB statement that computes the same."""

from __future__ import annotations

from contextvars import ContextVar

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from curator.functions.keyed import key32
from curator.functions.vectors import centres, dot, with_distance
from curator.functions.workspace import stash
from curator.operators import baselines, consensus, hygiene, lloyd, measures, mixing, probes, refine, resolution, sampling, theory
from curator.operators.features import cluster_features, znorm
from curator.plans.curation import blend
from curator.sources.tables import corpus_vec, table

QUERIES: dict = {}
ORACLES: dict = {}


_memo: ContextVar[dict | None] = ContextVar("steps of the query that is being built", default=None)


def once(f):
    """Within one query, the frame of an intermediate step is written once and read wherever it is used."""

    def get(spark, d):
        made, key = _memo.get(), (f.__name__, d)
        if made is None:
            return f(spark, d)
        if key not in made:
            made[key] = stash(f(spark, d), f.__name__)
        return made[key]

    return get


def query(sql: str | None = None):
    def add(f):
        def run(spark, d):
            token = _memo.set({})
            try:
                return f(spark, d)
            finally:
                _memo.reset(token)

        run.__name__, run.__doc__ = f.__name__, f.__doc__
        QUERIES[f.__name__] = run
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return add


def r6(df: DataFrame) -> DataFrame:
    """Doubles rounded to six places (and no negative zero)."""
    return df.select([(F.round(F.col(c), 6) + F.lit(0.0)).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


# ---------------------------------------------------------------- SQL building blocks
C = """c AS (SELECT d.doc_id, d.lang, d.source, len(regexp_extract_all(d.text, '[^ \\t\\n\\r\\f]+'))::BIGINT AS n_tokens,
  e.embedding::DOUBLE[] AS emb, e.label AS k FROM documents d JOIN embeddings e ON d.doc_id = e.vec_id)"""


def sql_centres(name: str, source: str, keys: str) -> str:
    """Unit mean vectors of the groups of ``keys``."""
    return f"""{name}_m AS (SELECT {keys}, list(v ORDER BY p) AS m FROM (SELECT {keys}, p, avg(v) AS v FROM (SELECT {keys}, unnest(emb) AS v, generate_subscripts(emb, 1) AS p FROM {source}) GROUP BY {keys}, p) GROUP BY {keys}),
{name} AS (SELECT {keys}, list_transform(m, lambda x: x / sqrt(list_sum(list_transform(m, lambda y: y * y)))) AS mu FROM {name}_m)"""


def sql_dist(name: str, source: str, mu: str, keys: str, out: str = "dist") -> str:
    return f"""{name} AS (SELECT {source}.*, sqrt(list_sum(list_transform(list_zip(emb, mu), lambda z: (z[1] - z[2]) * (z[1] - z[2])))) AS {out} FROM {source} JOIN {mu} USING ({keys}))"""


def sql_features(name: str, source: str, keys: str, dist: str = "dist") -> str:
    return f"""{name} AS (SELECT {keys}, sum(nl)::BIGINT AS n, 1 / (0.001 + sum(sd) / sum(nl)) AS z_coh, ln(1 + sum(nl)) AS z_size, ln(1 + sum(st) / sum(nl)) AS z_len,
  greatest(ln(sum(nl)) - sum(nl * ln(nl)) / sum(nl), 0.0) AS z_ent FROM (SELECT {keys}, lang AS lang_, count(*) AS nl, sum({dist}) AS sd, sum(n_tokens)::DOUBLE AS st FROM {source} GROUP BY {keys}, lang) GROUP BY {keys})"""


def sql_z(name: str, source: str) -> str:
    parts = ", ".join(f"CASE WHEN coalesce(stddev_pop(z_{f}) OVER (), 0) < 1e-12 THEN 0.0 ELSE (z_{f} - avg(z_{f}) OVER ()) / stddev_pop(z_{f}) OVER () END AS zn_{f}" for f in ("coh", "size", "len", "ent"))
    return f"{name} AS (SELECT *, {parts} FROM {source})"


FEATURES = ", ".join([C, sql_centres("mu", "c", "k"), sql_dist("a", "c", "mu", "k"), sql_features("f", "a", "k"), sql_z("z", "f")])
_o = {"coh": "zn_coh", "size": "-zn_size", "len": "-zn_len", "ent": "-zn_ent"}
CORR = "rho AS (" + " UNION ALL ".join(f"SELECT '{a}' AS f, '{b}' AS g, " + ("max(1.0::DOUBLE)" if a == b else f"coalesce((avg(({x}) * ({y})) - avg({x}) * avg({y})) / nullif(stddev_pop({x}) * stddev_pop({y}), 0), 0.0)") + " AS rho FROM z" for a, x in _o.items() for b, y in _o.items()) + ")"
POWER = """pw AS (SELECT 0 AS step, f, 0.25::DOUBLE AS v FROM (VALUES ('coh'), ('size'), ('len'), ('ent')) t(f)
  UNION ALL SELECT step + 1, f, v / sum(v) OVER () FROM (SELECT pw.step, rho.f, sum((1 + rho.rho) / 2 * pw.v) AS v FROM pw JOIN rho ON rho.g = pw.f WHERE pw.step < 30 GROUP BY pw.step, rho.f)),
w AS (SELECT f, v FROM pw WHERE step = 30)"""
_w = lambda f: f"(SELECT v FROM w WHERE f = '{f}')"
SCORES = f"s AS (SELECT *, {_w('coh')} * zn_coh - {_w('size')} * zn_size - {_w('len')} * zn_len - {_w('ent')} * zn_ent AS s FROM z)"
BUDGET = "b AS (SELECT *, exp(s - max(s) OVER ()) / sum(e) OVER () AS r FROM (SELECT *, exp(s - max(s) OVER ()) AS e FROM s))"
BASE = f"WITH RECURSIVE {FEATURES}, {CORR}, {POWER}, {SCORES}, {BUDGET}"

SUBS = ", ".join([
    "q AS (SELECT *, (doc_id % 4)::INT AS j FROM a)", sql_centres("mus", "q", "k, j"),
    "qs AS (SELECT q.*, sqrt(list_sum(list_transform(list_zip(emb, mu), lambda z: (z[1] - z[2]) * (z[1] - z[2])))) AS dist_sub FROM q JOIN mus USING (k, j))", sql_features("g", "qs", "k, j", "dist_sub"),
])
_mom = lambda f: f"sum(n * z_{f}) OVER (PARTITION BY k) / sum(n) OVER (PARTITION BY k) AS m_{f}, sqrt(greatest(sum(n * z_{f} * z_{f}) OVER (PARTITION BY k) / sum(n) OVER (PARTITION BY k) - power(sum(n * z_{f}) OVER (PARTITION BY k) / sum(n) OVER (PARTITION BY k), 2), 0)) AS sd_{f}"
_exc = lambda f: f"CASE WHEN sd_{f} < 1e-12 THEN 0 ELSE power(greatest((z_{f} - m_{f}) / sd_{f}, 0), 2) END"
PENALTY = f"p AS (SELECT *, {_exc('len')} + {_exc('ent')} AS l_struct FROM (SELECT *, {_mom('len')}, {_mom('ent')} FROM g))"
GATE = "h AS (SELECT p.*, exp(-0.5 * l_struct) AS penalty_factor, CASE WHEN p.n = 1 THEN 0.5 ELSE 1 / (1 + exp(f.z_coh - p.z_coh)) END AS beta FROM p JOIN f USING (k))"
PROBE = "pr AS (SELECT k, j, doc_id, row_number() OVER (PARTITION BY k, j ORDER BY dist_sub, doc_id)::INT AS rank FROM qs QUALIFY rank <= 3)"
LABEL = """ls AS (SELECT k, j, (coalesce(sum(good), 0) + 2.0 * any_value(rate)) / (count(good) + 2.0) AS p FROM pr LEFT JOIN (SELECT doc_id, (quality * (1 - toxic))::DOUBLE AS good FROM labels) USING (doc_id)
  CROSS JOIN (SELECT avg((quality * (1 - toxic))::DOUBLE) AS rate FROM labels) GROUP BY k, j)"""
WEIGHT = "ww AS (SELECT h.*, b.r, ls.p AS p_, b.r * ls.p * penalty_factor * (beta + 0.01) AS raw FROM h JOIN b USING (k) JOIN ls USING (k, j))"
FULL = f"{BASE}, {SUBS}, {PENALTY}, {GATE}, {PROBE}, {LABEL}, {WEIGHT}, wg AS (SELECT k, j, n, raw / sum(raw) OVER () AS w FROM ww)"
SUPPLY = "su AS (SELECT k, j, sum(n_tokens)::DOUBLE AS supply, any_value(w) AS w FROM qs JOIN wg USING (k, j) GROUP BY k, j)"
H = lambda x, purpose: f"('0x' || substr(md5('42:{purpose}:' || {x}), 1, 8))::BIGINT"


# ---------------------------------------------------------------- the same in Spark
@once
def assigned(spark: SparkSession, d: str) -> DataFrame:
    c = corpus_vec(spark, d)
    return with_distance(c, centres(c, ["k"]), ["k"])


@once
def feats(spark, d):
    return cluster_features(assigned(spark, d), ["k"])


@once
def scored(spark, d):
    z = znorm(feats(spark, d))
    return mixing.score(z, consensus.weights(z, "power"))


@once
def budgeted(spark, d):
    return mixing.budget(scored(spark, d))


@once
def subs(spark, d):
    a = assigned(spark, d).withColumn("j", (F.col("doc_id") % 4).cast("int"))
    return with_distance(a, centres(a, ["k", "j"]), ["k", "j"], "dist_sub")


@once
def sub_feats(spark, d):
    return cluster_features(subs(spark, d), ["k", "j"], "dist_sub")


@once
def gated(spark, d):
    return refine.gate(refine.penalty(sub_feats(spark, d)), feats(spark, d))


@once
def label_scores(spark, d):
    return probes.score_labels(probes.select(subs(spark, d)), table(spark, d, "labels"))


def weighted(spark, d, normalise="global"):
    rows = gated(spark, d).join(F.broadcast(budgeted(spark, d).select("k", "r")), "k").join(label_scores(spark, d), ["k", "j"])
    return refine.weight(rows, normalise=normalise)


@once
def cells(spark, d):
    supply = subs(spark, d).groupBy("k", "j").agg(F.sum("n_tokens").alias("supply"))
    return weighted(spark, d).select("k", "j", "w").join(supply, ["k", "j"])


@query(f"WITH {C} SELECT doc_id, round(sqrt(list_sum(list_transform(emb, lambda x: x * x))), 6) AS norm FROM c")
def vec_norms(spark, d):
    return r6(corpus_vec(spark, d).select("doc_id", F.sqrt(dot(F.col("emb"), F.col("emb"))).alias("norm")))


@query("""SELECT lang, count(*)::BIGINT AS docs, sum(n)::BIGINT AS tokens, max(n)::BIGINT AS longest, round(avg(n), 6) AS mean FROM (SELECT lang, len(regexp_extract_all(text, '[^ \\t\\n\\r\\f]+'))::BIGINT AS n FROM documents) GROUP BY lang""")
def token_stats(spark, d):
    from curator.functions.text import n_tokens

    t = table(spark, d, "documents").select("lang", n_tokens("text").alias("n"))
    return r6(t.groupBy("lang").agg(F.count(F.lit(1)).alias("docs"), F.sum("n").alias("tokens"), F.max("n").alias("longest"), F.avg("n").alias("mean")))


@query(f"WITH {FEATURES} SELECT k, round(z_ent, 6) + 0.0 AS entropy FROM f")
def lang_entropy_by_label(spark, d):
    return r6(feats(spark, d).select("k", F.col("z_ent").alias("entropy")))


@query(f"WITH {FEATURES} SELECT k, round(z_coh, 6) AS cohesion FROM f")
def cohesion_by_label(spark, d):
    return r6(feats(spark, d).select("k", F.col("z_coh").alias("cohesion")))


@query(f"WITH {FEATURES} SELECT k, n, round(z_coh, 6) AS z_coh, round(z_size, 6) AS z_size, round(z_len, 6) AS z_len, round(z_ent, 6) + 0.0 AS z_ent FROM f")
def cluster_features_label(spark, d):
    return r6(feats(spark, d))


@query(f"WITH {FEATURES} SELECT k, round(zn_coh, 6) + 0.0 AS zn_coh, round(zn_size, 6) + 0.0 AS zn_size, round(zn_len, 6) + 0.0 AS zn_len, round(zn_ent, 6) + 0.0 AS zn_ent FROM z")
def features_znorm(spark, d):
    return r6(znorm(feats(spark, d)).select("k", "zn_coh", "zn_size", "zn_len", "zn_ent"))


@query(f"WITH {FEATURES}, {CORR} SELECT f, g, round(rho, 6) + 0.0 AS rho FROM rho")
def consensus_corr(spark, d):
    return r6(consensus.correlations(znorm(feats(spark, d))))


@query(f"WITH RECURSIVE {FEATURES}, {CORR}, {POWER} SELECT f, round(v, 6) AS v FROM w")
def consensus_weights_power(spark, d):
    w = consensus.weights(znorm(feats(spark, d)), "power")
    return r6(spark.createDataFrame(list(w.items()), "f string, v double"))


@query()
def consensus_weights_variants(spark, d):
    """Weights by every affinity and correlation, beside the power steps."""
    z = znorm(feats(spark, d)).persist()
    rows = [(how, f, v) for how, w in (("spectral", consensus.weights(z)), ("abs", consensus.weights(z, kind="abs")), ("relu", consensus.weights(z, kind="relu")), ("spearman", consensus.weights(z, method="spearman")), ("uniform", consensus.weights(z, "uniform"))) for f, v in w.items()]
    z.unpersist()
    return spark.createDataFrame(rows, "how string, f string, v double")


@query(f"{BASE} SELECT k, round(s, 6) + 0.0 AS s FROM s")
def geometric_scores(spark, d):
    return r6(scored(spark, d).select("k", "s"))


@query(f"{BASE} SELECT k, round(r, 6) AS r FROM b")
def budget_softmax(spark, d):
    return r6(budgeted(spark, d).select("k", "r"))


@query(f"WITH {C} SELECT k, round(1.0 / count(*) OVER (), 6) AS r FROM (SELECT DISTINCT k FROM c)")
def budget_uniform(spark, d):
    return r6(mixing.uniform(corpus_vec(spark, d).select("k").distinct()))


SEEDS = f"m0 AS (SELECT (row_number() OVER (ORDER BY {H('doc_id', 'seeds')}, doc_id) - 1)::INT AS k_, emb AS mu FROM c QUALIFY k_ < 6)"
_cos = "list_sum(list_transform(list_zip(emb, mu), lambda z: z[1] * z[2]))"


def _sql_round(i: int) -> str:
    """Assignment to the centres m{i}, and the centres after it."""
    assign_ = f"x{i} AS (SELECT doc_id, emb, arg_min(k_, (-round({_cos}, 12), k_))::INT AS k_ FROM c_ CROSS JOIN m{i} GROUP BY doc_id, emb)"
    return assign_ + ", " + sql_centres(f"y{i}", f"x{i}", "k_") + f", m{i + 1} AS (SELECT m{i}.k_, coalesce(y{i}.mu, m{i}.mu) AS mu FROM m{i} LEFT JOIN y{i} USING (k_))"


ROUNDS = f"WITH {C}, c_ AS (SELECT doc_id, emb FROM c), {SEEDS}, " + ", ".join(_sql_round(i) for i in range(3))


@query(f"WITH {C} SELECT doc_id, {H('doc_id', 'seeds')} AS h FROM c ORDER BY h, doc_id LIMIT 6")
def seed_by_hash(spark, d):
    return corpus_vec(spark, d).select("doc_id", key32("doc_id", purpose="seeds").alias("h")).orderBy("h", "doc_id").limit(6)


@query(f"{ROUNDS} SELECT doc_id, k_ AS k FROM x0")
def kmeans_assign_step(spark, d):
    c = corpus_vec(spark, d).drop("k")
    return lloyd.assign(c, lloyd.seed_rows(c, 6)).select("doc_id", "k")


@query(f"{ROUNDS} SELECT k_ AS k, round(mu[1], 6) + 0.0 AS x1, round(mu[64], 6) + 0.0 AS x64 FROM m1")
def kmeans_update_step(spark, d):
    c = stash(corpus_vec(spark, d).drop("k"), "corpus")
    new, _ = lloyd.step(c, {6: lloyd.seed_rows(c, 6)})
    return r6(lloyd.frame(spark, new).select("k", F.col("mu")[0].alias("x1"), F.col("mu")[63].alias("x64")))


@query(f"{ROUNDS} SELECT k_ AS k, round(mu[1], 6) + 0.0 AS x1, round(mu[64], 6) + 0.0 AS x64 FROM m3")
def kmeans_three_rounds(spark, d):
    c = corpus_vec(spark, d).drop("k")
    return r6(lloyd.frame(spark, lloyd.sweep(c, [6], iters=3, tol=-1.0)).select("k", F.col("mu")[0].alias("x1"), F.col("mu")[63].alias("x64")))


PROBE20 = f"WITH {C}, c_ AS (SELECT doc_id, emb FROM c WHERE {H('doc_id', 'probe')} / 4294967296.0 < 0.2), c_all AS (SELECT doc_id, emb FROM c), {SEEDS.replace('FROM c ', 'FROM c_ ')}, {_sql_round(0)}"


@query(f"{PROBE20} SELECT doc_id, arg_min(k_, (-round({_cos}, 12), k_))::INT AS k FROM c_all CROSS JOIN m1 GROUP BY doc_id")
def assign_full_from_probe(spark, d):
    c = corpus_vec(spark, d).drop("k")
    probe = lloyd.probe_sample(c)
    return lloyd.assign(c, lloyd.sweep(probe, [6], iters=1)[6]).select("doc_id", "k")


@query()
def kmeans_library(spark, d):
    c = corpus_vec(spark, d).drop("k")
    return lloyd.assign(c, lloyd.fit_mllib(c, 6)).groupBy("k").agg(F.count(F.lit(1)).alias("n"), F.avg("dist").alias("mean_dist"))


@query()
def kmeans_spread_seeding(spark, d):
    c = corpus_vec(spark, d).drop("k")
    return lloyd.assign(c, lloyd.fit(c, 6, 5, how="parallel")).groupBy("k").agg(F.count(F.lit(1)).alias("n"), F.avg("dist").alias("mean_dist"))


FINE = ", ".join(["cf AS (SELECT *, (k * 10 + CASE lang WHEN 'de' THEN 0 WHEN 'en' THEN 1 WHEN 'es' THEN 2 ELSE 3 END)::INT AS j FROM c)", sql_centres("muf", "cf", "j"), sql_dist("af", "cf", "muf", "j"), sql_features("ff", "af", "j"), sql_z("zf", "ff")])
BRIDGE = """br AS (SELECT i, j, e / sum(e) OVER (PARTITION BY i) AS pi FROM (SELECT i, j, exp(20 * (c - max(c) OVER (PARTITION BY i))) AS e FROM
  (SELECT mu.k AS i, muf.j, list_sum(list_transform(list_zip(mu.mu, muf.mu), lambda z: z[1] * z[2])) AS c FROM mu CROSS JOIN muf)))"""
HAT = "sh AS (SELECT i, sum(pi * s) AS s_hat FROM br JOIN (SELECT j, 0.25 * (zn_coh - zn_size - zn_len - zn_ent) AS s FROM zf) USING (j) GROUP BY i), st AS (SELECT k AS i, s, s_hat FROM s JOIN sh ON sh.i = s.k)"


def fine(spark, d):
    order = F.when(F.col("lang") == "de", 0).when(F.col("lang") == "en", 1).when(F.col("lang") == "es", 2).otherwise(3)
    return corpus_vec(spark, d).withColumn("j", (F.col("k") * 10 + order).cast("int"))


def bridged(spark, d):
    return resolution.bridge(centres(corpus_vec(spark, d), ["k"]).withColumnRenamed("k", "i"), centres(fine(spark, d), ["j"]))


@once
def both_scores(spark, d):
    f = fine(spark, d)
    z = znorm(cluster_features(with_distance(f, centres(f, ["j"]), ["j"]), ["j"]))
    hat = resolution.reconstruct(bridged(spark, d), mixing.score(z, consensus.weights(z, "uniform")))
    return scored(spark, d).select(F.col("k").alias("i"), "s").join(hat, "i")


@query(f"WITH {FEATURES}, {FINE}, {BRIDGE} SELECT i, j, round(pi, 6) AS pi FROM br")
def bridge_softmax(spark, d):
    return r6(bridged(spark, d))


@query(f"{BASE}, {FINE}, {BRIDGE}, {HAT} SELECT i, round(s, 6) + 0.0 AS s, round(s_hat, 6) + 0.0 AS s_hat FROM st")
def reconstructed_scores(spark, d):
    return r6(both_scores(spark, d))


_TAU = "FROM (SELECT sign(a.s - b.s) AS dx, sign(a.s_hat - b.s_hat) AS dy FROM st a JOIN st b ON a.i < b.i)"


@query(f"{BASE}, {FINE}, {BRIDGE}, {HAT} SELECT round(sum(dx * dy) / sqrt(sum(abs(dx)) * sum(abs(dy))), 6) + 0.0 AS tau {_TAU}")
def kendall_tau_b(spark, d):
    return r6(resolution.tau(both_scores(spark, d)))


@query(f"{BASE}, {FINE}, {BRIDGE}, {HAT} SELECT round(sum(dx * dy) / count(*), 6) + 0.0 AS tau {_TAU}")
def kendall_tau_a(spark, d):
    return r6(resolution.tau(both_scores(spark, d), variant="a"))


@query(f"WITH {FEATURES} SELECT k AS K, round(z_coh, 6) AS J, round(z_coh - lag(z_coh) OVER (ORDER BY k), 6) + 0.0 AS dJ FROM f")
def stability_gain_lag(spark, d):
    return r6(resolution.gain(feats(spark, d).select(F.col("k").alias("K"), F.col("z_coh").alias("J"))))


@query(f"WITH {C} SELECT k, count(*)::BIGINT AS n, greatest(ceil(sqrt(count(*)))::INT, 1) AS m FROM c GROUP BY k")
def sub_counts_sqrt(spark, d):
    return refine.sub_counts(corpus_vec(spark, d).groupBy("k").agg(F.count(F.lit(1)).alias("n")))


@query(f"WITH {FEATURES}, {SUBS} SELECT k, j, n, round(z_coh, 6) AS z_coh, round(z_size, 6) AS z_size, round(z_len, 6) AS z_len, round(z_ent, 6) + 0.0 AS z_ent FROM g")
def subcluster_features(spark, d):
    return r6(sub_feats(spark, d))


@query(f"WITH {FEATURES}, {SUBS}, {PENALTY} SELECT k, j, round(l_struct, 6) + 0.0 AS l_struct FROM p")
def structural_penalty(spark, d):
    return r6(refine.penalty(sub_feats(spark, d)).select("k", "j", "l_struct"))


@query(f"WITH {FEATURES}, {SUBS}, {PENALTY} SELECT k, j, round(exp(-0.5 * l_struct), 6) AS penalty_factor FROM p")
def penalty_factor(spark, d):
    return r6(refine.penalty(sub_feats(spark, d)).select("k", "j", "penalty_factor"))


@query(f"WITH {FEATURES}, {SUBS}, {PENALTY}, {GATE} SELECT k, j, round(beta, 6) AS beta FROM h")
def cohesion_gate(spark, d):
    return r6(gated(spark, d).select("k", "j", "beta"))


@query(f"{FULL} SELECT k, j, round(w, 6) AS w FROM wg")
def subcluster_weight_global(spark, d):
    return r6(weighted(spark, d).select("k", "j", "w"))


@query(f"{FULL} SELECT k, j, round(r * raw / sum(raw) OVER (PARTITION BY k), 6) AS w FROM ww")
def subcluster_weight_within(spark, d):
    return r6(weighted(spark, d, "within").select("k", "j", "w"))


@query(f"WITH {FEATURES}, {SUBS}, {PROBE} SELECT k, j, doc_id, rank FROM pr")
def probe_topm(spark, d):
    return probes.select(subs(spark, d)).select("k", "j", "doc_id", "rank")


@query(f"WITH {FEATURES}, {SUBS}, {PROBE}, {LABEL} SELECT k, j, round(p, 6) AS p FROM ls")
def probe_label_score(spark, d):
    return r6(label_scores(spark, d))


@query(f"""{FULL}, {SUPPLY}, lv AS (SELECT *, sum(supply) OVER o AS cs, sum(w) OVER o AS cw, 0.5 * sum(supply) OVER () AS b, sum(w) OVER () AS aw FROM su WINDOW o AS (ORDER BY supply / w, k, j)),
lx AS (SELECT *, (b - (cs - supply)) / (aw - (cw - w)) AS level, supply / w AS ratio FROM lv), top AS (SELECT arg_min(level, ratio) AS level FROM lx WHERE level <= ratio)
SELECT k, j, round(least(supply, top.level * w), 3) + 0.0 AS quota FROM su CROSS JOIN top""")
def quota_waterfill(spark, d):
    c = cells(spark, d)
    volume = 0.5 * c.agg(F.sum("supply")).first()[0]
    return sampling.quotas(c, volume).select("k", "j", (F.round("quota", 3) + 0.0).alias("quota"))


QUOTA = f"{FULL}, {SUPPLY}, qu AS (SELECT k, j, supply, least(supply, 0.3 * sum(supply) OVER () * w) AS quota FROM su)"


def one_round(spark, d):
    c = cells(spark, d)
    return c.crossJoin(F.broadcast(c.agg((0.3 * F.sum("supply")).alias("all")))).withColumn("quota", F.least(F.col("supply").cast("double"), F.col("all") * F.col("w"))).drop("all")


@query(f"{QUOTA} SELECT k, j, round(quota, 3) + 0.0 AS quota FROM qu")
def quota_waterfill_one_round(spark, d):
    return one_round(spark, d).select("k", "j", (F.round("quota", 3) + 0.0).alias("quota"))


@query(f"{QUOTA} SELECT doc_id, k, j FROM (SELECT qs.doc_id, qs.k, qs.j, quota, sum(n_tokens) OVER (PARTITION BY qs.k, qs.j ORDER BY {H('doc_id', 'take')}, doc_id ROWS UNBOUNDED PRECEDING) AS run FROM qs JOIN qu USING (k, j)) WHERE run <= quota + 1e-9")
def sample_exact_tokens(spark, d):
    return sampling.take_exact(subs(spark, d), one_round(spark, d)).select("doc_id", "k", "j")


@query(f"{QUOTA} SELECT doc_id, k, j FROM qs JOIN qu USING (k, j) WHERE {H('doc_id', 'take')} / 4294967296.0 < quota / supply")
def sample_threshold(spark, d):
    return sampling.take_threshold(subs(spark, d), one_round(spark, d)).select("doc_id", "k", "j")


@query(f"{QUOTA} SELECT * FROM (SELECT doc_id, (floor(2.5 * quota / supply) + CASE WHEN {H('doc_id', 'take')} / 4294967296.0 < 2.5 * quota / supply - floor(2.5 * quota / supply) THEN 1 ELSE 0 END)::INT AS copies FROM qs JOIN qu USING (k, j)) WHERE copies > 0")
def sample_with_repeats(spark, d):
    q = one_round(spark, d).withColumn("quota", 2.5 * F.col("quota"))
    return sampling.take_repeat(subs(spark, d), q).select("doc_id", "copies")


@query("SELECT doc_id FROM documents WHERE ('0x' || substr(md5('42:epoch:' || doc_id), 1, 8))::BIGINT / 4294967296.0 < 0.5")
def epoch_half_prefix(spark, d):
    return sampling.epoch_prefix(table(spark, d, "documents").select("doc_id"), 0.5)


@query(f"WITH {FEATURES} SELECT round(avg(dist * dist), 6) AS quantisation FROM a")
def quantisation_term(spark, d):
    return r6(theory.quantisation(assigned(spark, d)))


GAINS = f"WITH {FEATURES}, sel AS (SELECT *, ({H('doc_id', 'random')} / 4294967296.0 < 0.4) AS chosen FROM a), gn AS (SELECT k, count(*)::BIGINT AS n, avg(dist * dist) AS sigma2, count(*) FILTER (chosen) AS n_sel, avg(dist * dist) FILTER (chosen) AS sel2 FROM sel GROUP BY k), ga AS (SELECT *, n / sum(n) OVER () AS alpha FROM gn)"


@once
def gains(spark, d):
    a = assigned(spark, d)
    return theory.gain(a, baselines.random(a.select("doc_id"), 0.4))


@query(f"{GAINS} SELECT round(sum(alpha * sel2), 6) AS pruning FROM ga")
def pruning_term(spark, d):
    return r6(theory.pruning(gains(spark, d)))


@query(f"{GAINS} SELECT round(sum(n_sel * sel2) / sum(n_sel), 6) AS pruning FROM ga")
def pruning_term_realised(spark, d):
    return r6(theory.pruning(gains(spark, d), "realised"))


@query(f"{GAINS} SELECT round(sum(alpha * sigma2), 6) AS quantisation, round(sum(alpha * sel2), 6) AS pruning, round(2 * sum(alpha * sigma2) + 2 * sum(alpha * sel2), 6) AS bound FROM ga")
def error_bound(spark, d):
    return r6(theory.bound(gains(spark, d)))


@query(f"{GAINS} SELECT k, n, round(alpha, 6) AS alpha, round(sigma2, 6) AS sigma2, n_sel::BIGINT AS n_sel, round(sel2, 6) AS sel2, round(sigma2 - sel2, 6) + 0.0 AS gain FROM ga")
def gain_per_cluster(spark, d):
    return r6(gains(spark, d))


def _sql_q(i: int, expr: str) -> str:
    return ", ".join([f"r{i} AS (SELECT doc_id, emb, ({expr})::INT AS g FROM c)", sql_centres(f"rm{i}", f"r{i}", "g"), f"rq{i} AS (SELECT count(DISTINCT g)::DOUBLE AS K, avg(d2) AS q FROM (SELECT g, list_sum(list_transform(list_zip(emb, mu), lambda z: (z[1] - z[2]) * (z[1] - z[2]))) AS d2 FROM r{i} JOIN rm{i} USING (g)))"])


@query(f"WITH {C}, " + ", ".join(_sql_q(i, e) for i, e in enumerate(("k % 2", "k % 5", "k"))) + " SELECT round(regr_slope(ln(q), ln(K)), 6) AS slope, round(-2 / regr_slope(ln(q), ln(K)), 4) AS dimension, round(exp(regr_intercept(ln(q), ln(K))), 6) AS constant FROM (SELECT * FROM rq0 UNION ALL SELECT * FROM rq1 UNION ALL SELECT * FROM rq2)")
def quantisation_rate_regr(spark, d):
    c, out = corpus_vec(spark, d), None
    for e in ("k % 2", "k % 5", "k"):
        g = c.withColumn("g", F.expr(e).cast("int"))
        q = with_distance(g, centres(g, ["g"]), ["g"]).agg(F.count_distinct("g").cast("double").alias("K"), F.avg(F.col("dist") * F.col("dist")).alias("quantisation"))
        out = q if out is None else out.unionByName(q)
    r = theory.rate(out)
    return r.select(F.round("slope", 6).alias("slope"), F.round("dimension", 4).alias("dimension"), F.round("constant", 6).alias("constant"))


@query(f"SELECT doc_id FROM documents WHERE {H('doc_id', 'random')} / 4294967296.0 < 0.3")
def baseline_random(spark, d):
    return baselines.random(table(spark, d, "documents").select("doc_id"), 0.3)


@query("""SELECT doc_id FROM (SELECT doc_id, sum(n) OVER (ORDER BY rating DESC, doc_id ROWS UNBOUNDED PRECEDING) AS run, 0.3 * sum(n) OVER () AS b FROM (SELECT doc_id, n, round(0.5 * least(1.0, n / 200.0) + 0.5 * CASE WHEN n_chars > 0 THEN (n_chars - digits)::DOUBLE / n_chars ELSE 0 END, 4) AS rating
 FROM (SELECT doc_id, n_chars, len(regexp_extract_all(text, '[^ \\t\\n\\r\\f]+')) AS n, n_chars - length(regexp_replace(text, '[0-9]', '', 'g')) AS digits FROM documents))) WHERE run <= b""")
def baseline_rating_topk(spark, d):
    from curator.functions.text import n_tokens

    digits = F.col("n_chars") - F.length(F.regexp_replace("text", "[0-9]", ""))
    docs = table(spark, d, "documents")
    n = n_tokens("text")
    rating = F.round(0.5 * F.least(F.lit(1.0), n / 200.0) + 0.5 * F.when(F.col("n_chars") > 0, (F.col("n_chars") - digits).cast("double") / F.col("n_chars")).otherwise(0.0), 4)
    s = stash(docs.select("doc_id", n.alias("n_tokens"), rating.alias("rating")), "ratings")
    return baselines.rating_selector(s, 0.3 * s.agg(F.sum("n_tokens")).first()[0]).select("doc_id")


@query()
def rating_logistic(spark, d):
    s = baselines.rated(table(spark, d, "documents"), labels=table(spark, d, "labels"))
    return baselines.rating_selector(s, 0.3 * s.agg(F.sum("n_tokens")).first()[0]).select("doc_id", "rating")


@query(f"SELECT doc_id FROM documents JOIN (SELECT source, least(1.0, 300.0 / count(*) OVER () / n) AS share FROM (SELECT source, count(*)::DOUBLE AS n FROM documents GROUP BY source)) USING (source) WHERE {H('doc_id', 'mix')} / 4294967296.0 < share")
def baseline_flat_mix(spark, d):
    return baselines.flat_mix(table(spark, d, "documents").select("doc_id", "source"), 300.0, "uniform").select("doc_id")


@query(f"SELECT doc_id FROM documents JOIN (SELECT lang, least(1.0, 300.0 * sqrt(n) / sum(sqrt(n)) OVER () / n) AS share FROM (SELECT lang, count(*)::DOUBLE AS n FROM documents GROUP BY lang)) USING (lang) WHERE {H('doc_id', 'mix')} / 4294967296.0 < share")
def baseline_temperature_mix(spark, d):
    return baselines.flat_mix(table(spark, d, "documents").select("doc_id", "lang"), 300.0, "temperature", "lang").select("doc_id")


@query(r"""SELECT doc_id FROM (SELECT doc_id, text, len(regexp_extract_all(text, '[^ \t\n\r\f]+')) AS n, greatest(length(text), 1)::DOUBLE AS size, string_split(text, chr(10)) AS ls FROM documents)
WHERE n BETWEEN 20 AND 20000 AND length(regexp_replace(text, '[^\p{L}\s.,;:''-]', '', 'g')) / size * (len(list_distinct(ls))::DOUBLE / len(ls)) >= 0.5 AND exp(-power((size / greatest(n, 1) - 6.5) / 3, 2)) >= 0.2""")
def baseline_rules(spark, d):
    return baselines.rules(table(spark, d, "documents")).select("doc_id")


@query()
def mixture_search(spark, d):
    docs = table(spark, d, "documents")
    held = docs.join(table(spark, d, "labels").where("quality = 1 and toxic = 0"), "doc_id", "left_semi")
    shares, seen = baselines.mixture_optimiser(docs, held, candidates=32, buckets=1024)
    best = max(c["value"] for c in seen)
    return spark.createDataFrame([(k, float(v), best, seen[0]["value"]) for k, v in shares.items()], "source string, share double, value double, natural_value double")


GLOBAL_PENALTY = PENALTY.replace("PARTITION BY k", "")
_all = f"{FEATURES}, {SUBS}, ca AS (SELECT *, 0 AS z0 FROM qs), " + sql_centres("mua", "ca", "z0") + ", aa AS (SELECT ca.lang, ca.n_tokens, z0, sqrt(list_sum(list_transform(list_zip(emb, mu), lambda z: (z[1] - z[2]) * (z[1] - z[2])))) AS dist FROM ca JOIN mua USING (z0)), " + sql_features("fa", "aa", "z0")


def _global_gate(spark, d):
    from curator.plans.curation import _corpus_features

    s = subs(spark, d)
    return refine.gate(refine.penalty(sub_feats(spark, d), "global"), _corpus_features(s))


@query(f"WITH {_all}, {GLOBAL_PENALTY}, {PROBE}, {LABEL}, x AS (SELECT p.k, p.j, 0.1 * ls.p * exp(-0.5 * l_struct) * (CASE WHEN p.n = 1 THEN 0.5 ELSE 1 / (1 + exp(fa.z_coh - p.z_coh)) END + 0.01) AS raw FROM p JOIN ls USING (k, j) CROSS JOIN fa) SELECT k, j, round(raw / sum(raw) OVER (), 6) AS w FROM x")
def ablation_no_macro_weights(spark, d):
    rows = _global_gate(spark, d).join(label_scores(spark, d), ["k", "j"]).withColumn("r", F.lit(0.1))
    return r6(refine.weight(rows).select("k", "j", "w"))


@query(f"WITH {_all}, {GLOBAL_PENALTY}, {PROBE}, {LABEL}, x AS (SELECT p.k, p.j, ls.p * exp(-0.5 * l_struct) * (CASE WHEN p.n = 1 THEN 0.5 ELSE 1 / (1 + exp(fa.z_coh - p.z_coh)) END + 0.01) AS raw FROM p JOIN ls USING (k, j) CROSS JOIN fa) SELECT k, j, round(raw / sum(raw) OVER (), 6) AS w FROM x")
def ablation_flat_scored_weights(spark, d):
    rows = _global_gate(spark, d).join(label_scores(spark, d), ["k", "j"]).withColumn("r", F.lit(1.0))
    return r6(refine.weight(rows).select("k", "j", "w"))


@query(f"WITH {FEATURES}, {SUBS} SELECT k, j, round(0.3 * sum(n_tokens), 3) AS quota FROM qs GROUP BY k, j")
def ablation_cluster_random_quota(spark, d):
    c = subs(spark, d).groupBy("k", "j").agg(F.sum("n_tokens").alias("supply")).withColumn("w", F.col("supply").cast("double"))
    return sampling.quotas(c, 0.3 * c.agg(F.sum("supply")).first()[0]).select("k", "j", F.round("quota", 3).alias("quota"))


@query(f"{BASE} SELECT k, round(least(supply, 0.3 * sum(supply) OVER () * r), 3) + 0.0 AS quota FROM (SELECT k, sum(n_tokens)::DOUBLE AS supply FROM a GROUP BY k) JOIN b USING (k)")
def ablation_no_micro_quota(spark, d):
    c = assigned(spark, d).groupBy("k").agg(F.sum("n_tokens").cast("double").alias("supply")).join(budgeted(spark, d).select("k", "r"), "k")
    return c.crossJoin(F.broadcast(c.agg((0.3 * F.sum("supply")).alias("all")))).select("k", (F.round(F.least(F.col("supply"), F.col("all") * F.col("r")), 3) + 0.0).alias("quota"))


def _sk(x: str) -> str:
    return f"(avg(power({x}, 3)) - 3 * avg({x}) * avg(power({x}, 2)) + 2 * power(avg({x}), 3)) / power(stddev_pop({x}), 3)"


@query(f"SELECT lang, round({_sk('n')}, 4) AS skew, round({_sk('ln(1 + n)')}, 4) AS skew_log, round(stddev_pop(n) / avg(n), 6) AS cv FROM (SELECT lang, len(regexp_extract_all(text, '[^ \\t\\n\\r\\f]+'))::DOUBLE AS n FROM documents) GROUP BY lang")
def feature_skewness(spark, d):
    from curator.functions.text import n_tokens

    t = table(spark, d, "documents").select("lang", n_tokens("text").cast("double").alias("n"))
    return t.groupBy("lang").agg(F.round(F.skewness("n"), 4).alias("skew"), F.round(F.skewness(F.log1p("n")), 4).alias("skew_log"), F.round(F.stddev_pop("n") / F.avg("n"), 6).alias("cv"))


@query(f"{GAINS} SELECT round(avg((n_sel > 0)::INT), 6) AS covered, round(sum(abs(n_sel / (SELECT sum(n_sel) FROM ga) - alpha)) / 2, 6) AS tv, round(-sum(CASE WHEN n_sel > 0 THEN n_sel / (SELECT sum(n_sel) FROM ga) * ln(n_sel / (SELECT sum(n_sel) FROM ga)) ELSE 0 END), 6) AS entropy FROM ga")
def coverage_tv(spark, d):
    a = assigned(spark, d)
    return r6(measures.coverage(a, baselines.random(a.select("doc_id"), 0.4)))


@query("SELECT min(doc_id) AS doc_id FROM documents GROUP BY text")
def exact_copies(spark, d):
    return hygiene.dedup_exact(table(spark, d, "documents")).select("doc_id")


_G = lambda t, key, n=8: f"SELECT DISTINCT {key}, list_slice(w, i, i + {n - 1}) AS g FROM (SELECT {key}, w, unnest(range(1, greatest(len(w) - {n - 1}, 1) + 1)) AS i FROM (SELECT {key}, regexp_extract_all(lower(text), '[^ \\t\\n\\r\\f]+') AS w FROM {t}) WHERE len(w) > 0)"


@query(f"""WITH RECURSIVE dg AS ({_G('documents', 'doc_id', 5)}), sz AS (SELECT doc_id, count(*) AS n FROM dg GROUP BY doc_id),
pr AS (SELECT a, b FROM (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM dg x JOIN dg y USING (g) WHERE x.doc_id <> y.doc_id GROUP BY 1, 2) JOIN sz sa ON sa.doc_id = a JOIN sz sb ON sb.doc_id = b WHERE c >= 0.8 * (sa.n + sb.n - c)),
r AS (SELECT a, b FROM pr UNION SELECT r.a, pr.b FROM r JOIN pr ON r.b = pr.a) SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT b FROM r WHERE a < b)""")
def near_copies_minhash(spark, d):
    return hygiene.dedup_near(table(spark, d, "documents")).select("doc_id")


@query("SELECT DISTINCT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)")
def contaminated_contains(spark, d):
    return hygiene.contains(table(spark, d, "documents"), table(spark, d, "benchmark")).distinct()


@query(f"""WITH dg AS ({_G('documents', 'doc_id', 3)}), ig AS ({_G('benchmark', 'item_id', 3)}), sd AS (SELECT doc_id, count(*) AS n FROM dg GROUP BY doc_id), si AS (SELECT item_id, count(*) AS n FROM ig GROUP BY item_id)
SELECT doc_id, item_id, round(c / (sd.n + si.n - c), 6) AS overlap FROM (SELECT doc_id, item_id, count(*) AS c FROM dg JOIN ig USING (g) GROUP BY doc_id, item_id) JOIN sd USING (doc_id) JOIN si USING (item_id) WHERE c >= 0.5 * (sd.n + si.n - c)""")
def contaminated_minhash(spark, d):
    """Documents near to an item as a whole."""
    return r6(hygiene.decontaminate(table(spark, d, "documents"), table(spark, d, "benchmark"), mode="minhash")[1])


@query(f"WITH dg AS ({_G('documents', 'doc_id')}), ig AS ({_G('benchmark', 'item_id')}), sz AS (SELECT item_id, count(*) AS size FROM ig GROUP BY item_id) SELECT doc_id, item_id, round(count(*) / any_value(size), 6) AS overlap FROM dg JOIN ig USING (g) JOIN sz USING (item_id) GROUP BY doc_id, item_id")
def contaminated_ngram(spark, d):
    return r6(hygiene.overlap(table(spark, d, "documents"), table(spark, d, "benchmark")))


@query("""WITH f AS (SELECT 'curated' AS component, doc_id, n_chars AS n FROM documents UNION ALL SELECT 'frozen', page_id, length(html) FROM pages), t AS (SELECT component, sum(n) AS have FROM f GROUP BY component)
SELECT component, count(*)::BIGINT AS docs, sum(n)::BIGINT AS volume FROM f JOIN t USING (component) WHERE ('0x' || substr(md5('53:random:' || doc_id), 1, 8))::BIGINT / 4294967296.0 < least(1.0, 1000000 * CASE component WHEN 'curated' THEN 7 ELSE 3 END / 10 / have) GROUP BY component""")
def blend_ratio(spark, d):
    docs = table(spark, d, "documents").select("doc_id", F.col("n_chars").alias("n_tokens"))
    pages = table(spark, d, "pages").select(F.col("page_id").alias("doc_id"), F.length("html").alias("n_tokens"))
    return blend(docs, pages, 1_000_000).groupBy("component").agg(F.count(F.lit(1)).alias("docs"), F.sum("n_tokens").alias("volume"))


@query("""WITH m AS (SELECT l_linestatus AS model, l_returnflag AS method, avg(l_quantity) AS q, avg(100 * l_discount) AS d, avg(100 * l_tax) AS t FROM lineitem GROUP BY 1, 2),
pub AS (SELECT model, method, 1.0::DOUBLE AS epoch, round(q, 2) AS printed, (q + d + t) / 3 AS mean FROM m), de AS (SELECT p.*, round(p.mean - q.mean + 1e-12, 1) + 0.0 AS delta FROM pub p JOIN pub q ON p.model = q.model AND q.method = 'N')
SELECT model, method, epoch, printed, round(mean + 1e-12, 4) AS mean, delta, CASE WHEN delta > 0 THEN 'up' WHEN delta < 0 THEN 'down' ELSE 'same' END AS sign FROM de""")
def published_avg(spark, d):
    """The averages of the published comparison, on measurements of a table: three metrics of each line status (model) and
    return flag (method), a number beside them, and the difference to the flag N."""
    line = table(spark, d, "lineitem").groupBy(F.col("l_linestatus").alias("model"), F.col("l_returnflag").alias("method"))
    by = line.agg(F.avg("l_quantity").alias("quantity"), F.avg(100 * F.col("l_discount")).alias("discount"), F.avg(100 * F.col("l_tax")).alias("tax"))
    results = by.select("model", "method", F.lit(1.0).alias("epoch"), F.round("quantity", 2).alias("printed"), "quantity", "discount", "tax")
    results = results.unpivot(["model", "method", "epoch", "printed"], ["quantity", "discount", "tax"], "metric", "value")
    return measures.averages(results, "N").withColumn("mean", F.round(F.col("mean") + 1e-12, 4))


@query()
def sliced_w2(spark, d):
    c = corpus_vec(spark, d)
    return theory.w2_sliced(c, baselines.random(c, 0.4), 16, 32)


@query("""WITH good AS (SELECT doc_id FROM labels WHERE quality = 1 AND toxic = 0), ws AS (SELECT doc_id, lang, unnest(regexp_extract_all(lower(text), '[^ \\t\\n\\r\\f]+')) AS w FROM documents),
b AS (SELECT doc_id, lang, ('0x' || substr(md5(w), 1, 8))::BIGINT % 16384 AS bucket, doc_id IN (SELECT doc_id FROM good) AS held FROM ws), m AS (SELECT bucket, count(*) AS c FROM b WHERE NOT held GROUP BY bucket),
s AS (SELECT lang, bucket, count(*) AS t FROM b WHERE held GROUP BY lang, bucket) SELECT lang, round(sum(t * ln((coalesce(c, 0) + 0.5) / ((SELECT sum(c) FROM m) + 0.5 * 16384))) / sum(t), 6) AS value FROM s LEFT JOIN m USING (bucket) GROUP BY lang""")
def proxy_cross_entropy(spark, d):
    docs = table(spark, d, "documents")
    good = table(spark, d, "labels").where("quality = 1 and toxic = 0")
    held = docs.join(good, "doc_id", "left_semi")
    return r6(measures.cross_entropy(docs.join(good, "doc_id", "left_anti"), held))


_count = lambda pattern: f"len(regexp_extract_all(text, '{pattern}'))::DOUBLE"


@query(f"""SELECT doc_id, round(1 - abs(o - c) / greatest(o + c, 1), 6) + 0.0 AS balanced, round(i / ls, 6) AS laid_out, round(least(1.0, 20 * s / greatest(n, 1)), 6) AS symbols FROM (SELECT doc_id, {_count(r'[(\[{]')} AS o, {_count(r'[)\]}]')} AS c,
{_count('(?m)^[ \\t]+[^ \\t\\n]')} AS i, {_count('[(){};=<>]')} AS s, length(text)::DOUBLE AS n, len(string_split(text, chr(10)))::DOUBLE AS ls FROM documents)""")
def rating_code(spark, d):
    """The ratings that the adapter to program text brings in."""
    return r6(baselines.rated(table(spark, d, "documents"), adapter=baselines.code_raters).select("doc_id", "balanced", "laid_out", "symbols"))


@query(f"{QUOTA} SELECT doc_id, k, j FROM qs JOIN qu USING (k, j) WHERE {H('doc_id', 'take')} / 4294967296.0 < quota / supply")
def curate_given_clusters(spark, d):
    """The whole method with the given labels as clusters: what ``entry()`` returns."""
    return sampling.take_threshold(subs(spark, d), one_round(spark, d)).select("doc_id", "k", "j")


@query()
def curate_full(spark, d):
    from curator.plans.workloads import Lab

    return Lab(spark, d).full().subset


@query()
def k_sweep_text(spark, d):
    from curator.plans.workloads import k_sweep

    return k_sweep(spark, d, repeats=1)




ORACLES["wl_decontaminate"] = f"""WITH dg AS ({_G('documents', 'doc_id')}), ig AS ({_G('benchmark', 'item_id')}), sz AS (SELECT item_id, count(*) AS size FROM ig GROUP BY item_id),
bad AS (SELECT DISTINCT doc_id FROM (SELECT doc_id, item_id, count(*) / any_value(size) AS o FROM dg JOIN ig USING (g) JOIN sz USING (item_id) GROUP BY doc_id, item_id) WHERE o >= 0.5),
v AS (SELECT DISTINCT doc_id FROM documents d JOIN benchmark b ON contains(d.text, b.text))
SELECT 'decontaminate' AS workload, method, 1.0::DOUBLE AS epoch, metric, 'all' AS lang, value::DOUBLE AS value FROM (SELECT 'before' AS method, 'verbatim' AS metric, count(*) AS value FROM v
UNION ALL SELECT 'after', 'verbatim', count(*) FROM v ANTI JOIN bad USING (doc_id) UNION ALL SELECT 'ngram', 'removed', count(*) FROM bad)"""
