"""The experiments, re-expressed on the given tables; every workload returns rows of (workload, method, epoch, metric, lang, value).

The proxies stand in for trained models' scores and claim nothing about them.
"""

from __future__ import annotations

import time
from dataclasses import replace

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from curator.functions.keyed import draw
from curator.functions.text import n_tokens, strip_html
from curator.functions.workspace import stash
from curator.operators import baselines, consensus, hygiene, lloyd, measures, probes, refine, resolution, sampling, theory
from curator.plans import curation
from curator.plans.curation import CurationPlan
from curator.sources.tables import table

SCHEMA = "workload string, method string, epoch double, metric string, lang string, value double"
#: The published defaults: K is searched, sub-clusters follow the square root of the population.
PLAN = CurationPlan()
#: Budgets of the curves, as shares of an epoch.
PARTS = (0.05, *(i / 10 for i in range(1, 11)))
#: What is reported about a subset.
PROXIES = ("entropy", "quality", "cells", "tokens")


class Lab:
    """Tables and subsets that the workloads of one folder share, each built once."""

    def __init__(self, spark: SparkSession, sf_dir: str, plan: CurationPlan = PLAN, same: Lab | None = None):
        """``same``: a lab of the same folder whose corpus, and what no seed changes, is taken over."""
        self.spark, self.dir, self.plan = spark, sf_dir, plan
        self.docs, self.labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
        self._made: dict = {k: v for k, v in same._made.items() if k in ("store", "tokens", "counted", "subset rating selector")} if same else {}

    def once(self, name: str, make):
        if name not in self._made:
            self._made[name] = make()
        return self._made[name]

    @property
    def apart(self) -> DataFrame:
        """Good labelled documents, kept out of every method's corpus: half to tune by, half to judge by."""
        good = self.labels.where("quality = 1 and toxic = 0").select("doc_id")
        return self.docs.join(good, "doc_id", "left_semi").where(F.col("doc_id") % 5 == 0)

    @property
    def validation(self) -> DataFrame:
        """What a method may look at to choose its settings."""
        return self.apart.where(draw("doc_id", purpose="validation") < 0.5)

    @property
    def held_out(self) -> DataFrame:
        """What only measures look at."""
        return self.apart.where(draw("doc_id", purpose="validation") >= 0.5)

    @property
    def corpus(self) -> tuple[DataFrame, DataFrame]:
        """Documents that methods may choose from, before items and copies leave, and the benchmark."""
        return self.docs.join(self.apart.select("doc_id"), "doc_id", "left_anti"), table(self.spark, self.dir, "benchmark")

    @property
    def store(self) -> DataFrame:
        return self.once("store", lambda: curation.front_end(*self.corpus))

    @property
    def lengths(self) -> DataFrame:
        """(doc_id, n_tokens) of the store, for those who need no vectors."""
        return self.once("lengths", lambda: stash(curation.cleaned(*self.corpus).select("doc_id", "n_tokens"), "lengths"))

    @property
    def tokens(self) -> int:
        return self.once("tokens", lambda: self.store.agg(F.sum("n_tokens")).first()[0])

    @property
    def resolutions(self) -> curation.Resolutions:
        return self.once("resolutions", lambda: curation.resolutions(self.store, self.plan))

    @property
    def macro(self) -> curation.Macro:
        return self.once("macro", lambda: curation.macro(self.store, self.plan, self.resolutions if self.plan.k is None else None))

    def k_total(self) -> int:
        counts = refine.sub_counts(self.macro[1].select("k", "n"), self.plan.sub_c, self.plan.sub_cap)
        return int(counts.agg(F.sum("m")).first()[0])

    def flat(self) -> DataFrame:
        return self.once("flat", lambda: curation.flat_clusters(self.store, self.plan, self.k_total()))

    def full(self):
        return self.once("full", lambda: curation.curate(self.store, self.plan, self.docs, self.labels, self.macro))

    def subset(self, method: str) -> DataFrame:
        def make():
            share = self.plan.budget.volume(self.tokens) / self.tokens
            corpus = self.docs.join(self.store.select("doc_id"), "doc_id", "left_semi")
            if method == "random":
                rows = baselines.random(self.store, share, self.plan.seed)
            elif method == "rating selector":
                rows = baselines.rating_selector(baselines.rated(corpus, labels=self.labels), share * self.tokens)
            elif method == "mixture optimiser":
                counted = self.once("counted", lambda: baselines.counted(corpus, self.validation))
                shares, seen = baselines.mixture_optimiser(corpus, self.validation, seed=self.plan.seed, given=counted)
                self._made["proxy fits"] = len(seen)
                rows = baselines.by_shares(self.store, shares, share * self.store.count(), seed=self.plan.seed)
            elif method == "rating selector, code":
                rows = baselines.rating_selector(baselines.rated(corpus, labels=self.labels, adapter=baselines.code_raters), share * self.tokens)
            elif method == "rules":
                rows = baselines.rules(corpus).select("doc_id")
            elif method == "curator":
                rows = self.full().subset
            elif method == "no macro":
                rows = curation.no_macro(self.store, self.plan, self.docs, self.labels, self.macro, self.full().sub).subset
            elif method == "no micro":
                rows = curation.no_micro(self.store, self.plan, self.macro).subset
            elif method == "flat random":
                rows = curation.flat_random(self.store, self.plan, self.k_total(), self.flat()).subset
            else:
                rows = curation.flat_scored(self.store, self.plan, self.k_total(), self.docs, self.labels, self.flat()).subset
            return stash(rows.select("doc_id").distinct(), "subset")

        return self.once(f"subset {method}", make)

    def proxies(self, workload: str | dict[int, str], runs: list[tuple[str, float, DataFrame]], metrics: tuple[str, ...] = PROXIES) -> DataFrame:
        """Held-out cross-entropy by language, label quality, coverage and tokens of each (method, epoch, ids), a scan for all of them.

        ``workload``: a name, or one for each number of buckets of the entropy's model.
        """
        names = workload if isinstance(workload, dict) else {1 << 14: workload}
        out = []
        for a in range(0, len(runs), measures.MOST):
            part = runs[a : a + measures.MOST]
            n, owners = len(part), measures.members([ids for _, _, ids in part])
            once = lambda df, metric, lang="lang": df.select("i", metric.alias("metric"), (F.col(lang) if lang == "lang" else F.lit(lang)).alias("lang"), "value")
            common = []
            if "quality" in metrics:
                common.append(once(measures.qualities(self.labels, owners, n), F.lit("quality"), "all"))
            if "cells" in metrics:
                cover = measures.coverages(self.macro[0], owners, n).select("i", F.explode(F.array(*[F.struct(F.lit(f"cells_{c}").alias("metric"), F.col(c).cast("double").alias("value")) for c in ("covered", "tv", "entropy")])).alias("x"))
                common.append(once(cover.select("i", "x.metric", "x.value"), F.col("metric"), "all"))
            if "tokens" in metrics:
                common.append(once(measures.token_shares(self.docs, owners, n), F.lit("tokens")))
            rows = [df.select(F.lit(name).alias("workload"), *df.columns) for df in common for name in names.values()]
            if "entropy" in metrics:
                named = F.create_map(*[F.lit(x) for b, name in names.items() for x in (b, name)])[F.col("buckets")]
                entropy = measures.cross_entropies(self.docs, owners, n, self.held_out, tuple(names))
                rows.append(entropy.select(named.alias("workload"), "i", F.lit("entropy").alias("metric"), "lang", "value"))
            who = self.spark.createDataFrame([(i, m, float(e)) for i, (m, e, _) in enumerate(part)], "i int, method string, epoch double")
            out.append(_union(rows).join(F.broadcast(who), "i").select("workload", "method", "epoch", "metric", "lang", "value"))
        return _union(out)


def _rows(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame([(w, m, float(e), k, lang, None if v is None else float(v)) for w, m, e, k, lang, v in rows], SCHEMA)


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def main_compare(spark, sf_dir):
    lab = Lab(spark, sf_dir)
    runs = [(m, 1.0, lab.subset(m)) for m in MAIN]
    return lab.proxies("main", [*runs, ("curator", 0.5, sampling.epoch_prefix(lab.subset("curator"), 0.5))])


MAIN = ("random", "rating selector", "mixture optimiser", "curator")
ABLATIONS = ("random", "flat random", "flat scored", "no micro", "no macro", "curator")


def seed_spread(spark, sf_dir, seeds: int = 5, methods: tuple[str, ...] = MAIN, plan: CurationPlan = PLAN):
    """The main comparison (or other methods) once for each seed; mean, least and most of each measure tell a ranking from chance."""
    runs, lab = [], None
    for k in range(seeds):
        lab = Lab(spark, sf_dir, replace(plan, seed=plan.seed + 1000 * k), lab)
        runs += [(m, 1.0, lab.subset(m)) for m in methods]
    # corpus, labels and held-out texts are the same for all seeds, so one scan measures all of their subsets
    many = lab.proxies("seeds", runs, ("entropy", "quality")).groupBy("workload", "method", "epoch", "metric", "lang")
    spread = many.agg(F.avg("value").alias("mean"), F.min("value").alias("least"), F.max("value").alias("most"))
    kinds = F.explode(F.array(*[F.struct(F.lit(c).alias("name"), F.col(c).alias("value")) for c in ("mean", "least", "most")])).alias("x")
    rows = spread.select("workload", "method", "epoch", "metric", "lang", kinds)
    return rows.select("workload", "method", "epoch", F.concat_ws("_", "metric", "x.name").alias("metric"), "lang", "x.value")


def capacity_scaling(spark, sf_dir):
    lab = Lab(spark, sf_dir)
    runs = [("random", 1.0), ("curator", 0.5), ("curator", 1.0)]
    runs = [(m, e, sampling.epoch_prefix(lab.subset(m), e) if e < 1 else lab.subset(m)) for m, e in runs]
    return lab.proxies({1 << b: f"capacity 2^{b}" for b in (14, 16)}, runs)


def ablation(spark, sf_dir):
    lab = Lab(spark, sf_dir)
    return lab.proxies("ablation", [(m, 1.0, lab.subset(m)) for m in ABLATIONS])


def by_language(spark, sf_dir):
    """Values and token shares by language, the gap to the rating selector, and both for the languages with fewer tokens
    than the mean ('low') and the others ('high')."""
    lab = Lab(spark, sf_dir)
    methods = ("rating selector", "no macro", "curator")
    mine = stash(lab.proxies("language", [(m, 1.0, lab.subset(m)) for m in methods], ("entropy", "tokens")), "language")
    sizes = lab.store.groupBy("lang").agg(F.sum("n_tokens").alias("t"))
    group = sizes.crossJoin(F.broadcast(sizes.agg(F.avg("t").alias("mean")))).select("lang", F.when(F.col("t") < F.col("mean"), "low").otherwise("high").alias("group"))
    ours = mine.where("metric = 'entropy'")
    ref = ours.where("method = 'rating selector'").select("lang", F.col("value").alias("ref"))
    gap = ours.where("method <> 'rating selector'").join(F.broadcast(ref), "lang").select("workload", "method", "epoch", F.lit("gap to rating selector").alias("metric"), "lang", (F.col("value") - F.col("ref")).alias("value"))
    both = ours.unionByName(gap)
    apart = both.join(F.broadcast(group), "lang").groupBy("workload", "method", "epoch", "metric", "group").agg(F.avg("value").alias("value")).withColumnRenamed("group", "lang")
    by_source = measures.token_shares(lab.docs, measures.members([lab.subset(m) for m in methods]), len(methods), "source")
    by_source = by_source.select(F.lit("source").alias("workload"), F.array(*[F.lit(m) for m in methods])[F.col("i")].alias("method"), F.lit(1.0).alias("epoch"), F.lit("tokens").alias("metric"), F.col("source").alias("lang"), "value")
    return _union([mine, gap, apart, by_source])


def k_sweep(spark, sf_dir, grid: tuple[int, ...] = PLAN.grid, repeats: int = 3):
    """J of every K (mean, least and most over seeds), its gain over the K before, and the K that each rule chooses."""
    lab = Lab(spark, sf_dir)
    plan = replace(lab.plan, k=None, grid=grid, repeats=repeats)
    values = curation.stability(lab.store, plan)[0][plan.scale]
    curve = [(k, sum(v) / len(v) if v else None) for k, v in values.items()]
    rows = resolution.gain(spark.createDataFrame(curve, "K int, J double"))
    parts = [rows.select(F.lit("k sweep").alias("workload"), F.concat(F.lit("K="), "K").alias("method"), F.lit(1.0).alias("epoch"), F.lit(n).alias("metric"), F.lit("all").alias("lang"), F.col(n).alias("value")) for n in ("J", "dJ")]
    ends = [("k sweep", f"K={k}", 1, name, "all", f(v)) for k, v in values.items() if v for name, f in (("J least", min), ("J most", max))]
    parts.append(_rows(spark, ends + [("k sweep", rule, 1, "K*", "all", resolution.choose(curve, rule)) for rule in ("argmax", "plateau")]))
    return _union(parts)


def landscape(spark, sf_dir):
    """Sub-clusters of the largest cluster: score, penalty factor, cohesion, weight, and the weight's rank correlations there."""
    full = Lab(spark, sf_dir).full()
    top = full.budget.orderBy(F.desc("n"), "k").select("k").first()[0]
    rows = stash(full.weights.where(F.col("k") == top), "landscape")
    cols = ("p", "l_struct", "penalty_factor", "z_coh", "beta", "w")
    long = rows.select(F.concat(F.lit("k"), "k", F.lit("/j"), "j").alias("method"), F.explode(F.array(*[F.struct(F.lit(c).alias("m"), F.col(c).cast("double").alias("v")) for c in cols])).alias("x"))
    long = long.select(F.lit("landscape").alias("workload"), "method", F.lit(1.0).alias("epoch"), F.col("x.m").alias("metric"), F.lit("all").alias("lang"), F.col("x.v").alias("value"))
    # one cluster's sub-clusters: a few thousand rows; ties share their mean rank
    mean_rank = lambda c: F.rank().over(Window.partitionBy("k").orderBy(c)) + (F.count(F.lit(1)).over(Window.partitionBy("k", c)) - 1) / 2
    ranked = rows.select(*[mean_rank(c).alias(c) for c in cols])
    ranks = ranked.agg(*[consensus.safe_corr("w", c).alias(c) for c in cols[:-1]]).first()
    return long.unionByName(_rows(spark, [("landscape", f"k{top}", 1, f"rank corr(w,{c})", "all", ranks[c]) for c in cols[:-1]]))


def feature_shape(spark, sf_dir):
    # both are written, as each measure below reads them again
    docs = stash(table(spark, sf_dir, "documents").select(n_tokens("text").alias("n_tokens")), "lengths")
    full = Lab(spark, sf_dir).full()
    clusters = full.sub.groupBy("k", "j").agg(F.count(F.lit(1)).alias("size"), (1 / (1e-3 + F.avg("dist_sub"))).alias("cohesion"), F.avg("n_tokens").alias("length"))
    clusters = stash(clusters, "shapes")
    parts = []
    for where, df, names in (("documents", docs, ["n_tokens"]), ("sub-clusters", clusters, ["size", "cohesion", "length"])):
        shape = measures.shape(df, names)
        cols = ("skew", "skew_log", "kurt", "kurt_log", "cv")
        long = shape.select("feature", F.explode(F.array(*[F.struct(F.lit(c).alias("m"), F.col(c).alias("v")) for c in cols])).alias("x"))
        parts.append(long.select(F.lit("shape").alias("workload"), F.lit(where).alias("method"), F.lit(1.0).alias("epoch"), F.concat("feature", F.lit("."), "x.m").alias("metric"), F.lit("all").alias("lang"), F.col("x.v").alias("value")))
        for n in names:
            for label, frame in (("ks", df), ("ks_log", df.withColumn(n, F.log1p(n)))):
                ks = measures.ks_normal(frame.withColumn(n, F.col(n).cast("double")), n)
                parts.append(ks.select(F.lit("shape").alias("workload"), F.lit(where).alias("method"), F.lit(1.0).alias("epoch"), F.lit(f"{n}.{label}").alias("metric"), F.lit("all").alias("lang"), F.col("ks").alias("value")))
    return _union(parts)


def _named(methods: tuple[str, ...]) -> Column:
    """The method of number ``i``."""
    return F.array(*[F.lit(m) for m in methods])[F.col("i")].alias("method")


def _curves(lab: Lab, workload: str, methods: tuple[str, ...], parts: tuple[float, ...]) -> DataFrame:
    """Held-out entropy by language at nested parts of the methods' subsets, out of one scan."""
    v = measures.cross_entropy_curves(lab.docs, measures.members([lab.subset(m) for m in methods]), len(methods), lab.held_out, parts)
    return v.select(F.lit(workload).alias("workload"), _named(methods), F.col("part").alias("epoch"), F.lit("entropy").alias("metric"), "lang", "value")


def efficiency(spark, sf_dir, parts: tuple[float, ...] = PARTS):
    lab = Lab(spark, sf_dir)
    rows = stash(_curves(lab, "efficiency", ("random", "curator"), parts), "efficiency")
    rows = rows.groupBy("workload", "method", "epoch", "metric").agg(F.avg("value").alias("value")).select("workload", "method", "epoch", "metric", F.lit("all").alias("lang"), "value")
    curves: dict[str, list[tuple[float, float]]] = {"random": [], "curator": []}
    for r in rows.collect():  # a row per method and part
        if r["value"] is not None:
            curves[r["method"]].append((r["epoch"], r["value"]))
    return rows.unionByName(_rows(spark, [("efficiency", "curator", 1, "times random", "all", measures.efficiency(curves["random"], curves["curator"]))]))


def blend(spark, sf_dir):
    lab = Lab(spark, sf_dir)
    pages = table(spark, sf_dir, "pages").select(F.col("page_id").alias("doc_id"), strip_html("html").alias("text")).select("doc_id", n_tokens("text").alias("n_tokens"))
    pages = stash(pages, "pages")
    mixed = curation.blend(lab.lengths, pages, 0.5 * pages.agg(F.sum("n_tokens")).first()[0] / 0.3)
    by = mixed.groupBy("component").agg(F.sum("n_tokens").cast("double").alias("value"))
    return by.select(F.lit("blend").alias("workload"), F.col("component").alias("method"), F.lit(1.0).alias("epoch"), F.lit("tokens").alias("metric"), F.lit("all").alias("lang"), "value")


def decontaminate(spark, sf_dir):
    docs, bench = table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")
    kept, audit = hygiene.decontaminate(docs, bench)
    # a document has an item's text or not whatever others are kept: one search serves before and after
    verbatim, left = stash(hygiene.contains(docs, bench).select("doc_id").distinct(), "verbatim"), kept.select("doc_id").distinct()
    return _rows(spark, [("decontaminate", "before", 1, "verbatim", "all", verbatim.count()), ("decontaminate", "after", 1, "verbatim", "all", verbatim.join(left, "doc_id", "left_semi").count()), ("decontaminate", "ngram", 1, "removed", "all", audit.select("doc_id").distinct().count())])


def probe_scale(spark, sf_dir, k: int = 12):
    """Centres from a fifth of the corpus against centres from all of it: agreement of the assignments (adjusted Rand)."""
    lab = Lab(spark, sf_dir)
    a = lloyd.assign(lab.store, lloyd.fit(lloyd.probe_sample(lab.store), k, lab.plan.iters), k="ka", dist="da")
    b = lloyd.assign(lab.store, lloyd.fit(lab.store, k, lab.plan.iters), k="kb", dist="db")
    cells = a.join(b, "doc_id").groupBy("ka", "kb").count().collect()  # K^2 cells at most
    pairs = lambda n: n * (n - 1) / 2
    rows, cols, n, index = {}, {}, 0, 0.0
    for c in cells:
        rows[c["ka"]] = rows.get(c["ka"], 0) + c["count"]
        cols[c["kb"]] = cols.get(c["kb"], 0) + c["count"]
        n += c["count"]
        index += pairs(c["count"])
    sa, sb = sum(map(pairs, rows.values())), sum(map(pairs, cols.values()))
    expected = sa * sb / max(pairs(n), 1)
    rand = (index - expected) / ((sa + sb) / 2 - expected) if (sa + sb) / 2 != expected else 1.0
    return _rows(spark, [("probe", "20%", 1, "adjusted rand", "all", rand), ("probe", "20%", 1, "samples", "all", n)])


def hyper(spark, sf_dir):
    """Penalty strength, gate floor and bridge scale: entropy of the weights, or stability of every K."""
    lab = Lab(spark, sf_dir)
    full = lab.full()
    rows = []
    spread = lambda w: w.agg((-F.sum(F.when(F.col("w") > 0, F.col("w") * F.log("w")).otherwise(0.0))).alias("e")).first()[0]
    base = full.weights.drop("w", "penalty_factor")
    for lam in (0.0, 0.25, 0.5, 1.0, 2.0):
        rows.append(("hyper", f"lambda={lam}", 1, "weight entropy", "all", spread(refine.weight(base.withColumn("penalty_factor", F.exp(-F.lit(lam) * F.col("l_struct")))))))
    for eps in (0.0, 0.01, 0.1):
        rows.append(("hyper", f"epsilon={eps}", 1, "weight entropy", "all", spread(refine.weight(full.weights.drop("w"), eps))))
    scales = (5.0, 10.0, 20.0, 40.0)
    for scale, values in curation.stability(lab.store, lab.plan, scales, lab.resolutions)[0].items():
        rows += [("hyper", f"scale={scale:g}", 1, f"J at K={k}", "all", sum(v) / len(v)) for k, v in values.items() if v]
    return _rows(spark, rows)


def saturation(spark, sf_dir):
    got = probes.saturation(Lab(spark, sf_dir).full().weights)
    long = got.select("stage", F.explode(F.array(*[F.struct(F.lit(c).alias("m"), F.col(c).cast("double").alias("v")) for c in ("top_share", "entropy")])).alias("x"))
    return long.select(F.lit("saturation").alias("workload"), F.col("stage").alias("method"), F.lit(1.0).alias("epoch"), F.col("x.m").alias("metric"), F.lit("all").alias("lang"), F.col("x.v").alias("value"))


def progress_radar(spark, sf_dir, parts: tuple[float, ...] = PARTS[1:]):
    return _curves(Lab(spark, sf_dir), "progress", ("random", "curator"), parts)


def overhead(spark, sf_dir):
    """Seconds and model calls: graded probes against graded documents and proxy evaluations."""
    lab = Lab(spark, sf_dir)
    lab.store.count()
    rows = []
    for m in ("curator", "rating selector", "mixture optimiser"):
        began = time.time()
        lab.subset(m).count()
        rows.append(("overhead", m, 1, "seconds", "all", time.time() - began))
    cells = lab.full().weights.count()
    rows += [("overhead", "curator", 1, "graded", "all", cells * lab.plan.probes), ("overhead", "rating selector", 1, "graded", "all", lab.store.count()), ("overhead", "mixture optimiser", 1, "proxy fits", "all", lab._made["proxy fits"])]
    return _rows(spark, rows)


def suite_groups(spark, sf_dir):
    """Published metrics by group, and the proxy on short and long held-out documents."""
    pub = measures.published(spark)
    group = F.when(F.col("metric").isin(*measures.GROUPS["generation"]), "generation").otherwise("reasoning")
    out = pub.groupBy("model", "method", "epoch", group.alias("metric")).agg(F.avg("value").alias("value"))
    out = out.select(F.concat(F.lit("published "), "model").alias("workload"), "method", "epoch", "metric", F.lit("all").alias("lang"), "value")
    lab = Lab(spark, sf_dir)
    held = lab.held_out.withColumn("lang", F.when(n_tokens("text") < 200, "short").otherwise("long"))
    methods = ("random", "curator")
    v = measures.cross_entropies(lab.docs, measures.members([lab.subset(m) for m in methods]), len(methods), held)
    return out.unionByName(v.select(F.lit("groups").alias("workload"), _named(methods), F.lit(1.0).alias("epoch"), F.lit("entropy").alias("metric"), "lang", "value"))


def error_bound(spark, sf_dir):
    """Quantisation, pruning, bound, sliced cost and kept-dropped distances of each method's subset."""
    lab = Lab(spark, sf_dir)
    assigned = lab.full().assigned
    parts = []
    for m in ("random", "curator"):
        ids = lab.subset(m)
        gains = stash(theory.gain(assigned, ids), "gains")
        b = theory.bound(gains)
        s = theory.w2_sliced(assigned, assigned.join(ids, "doc_id", "left_semi"), 16, 32)
        for df, names in ((b, ("quantisation", "pruning", "bound")), (s, ("w2_sliced",)), (theory.pruning(gains, "realised"), ("pruning",))):
            for n in names:
                label = n if n != "pruning" or df is b else "pruning realised"
                parts.append(df.select(F.lit("error").alias("workload"), F.lit(m).alias("method"), F.lit(1.0).alias("epoch"), F.lit(label).alias("metric"), F.lit("all").alias("lang"), F.col(n).cast("double").alias("value")))
        r = measures.rejected(assigned, ids)
        parts.append(r.select(F.lit("error").alias("workload"), F.lit(m).alias("method"), F.lit(1.0).alias("epoch"), F.concat(F.when(F.col("kept"), "kept").otherwise("dropped"), F.lit(" distance")).alias("metric"), F.lit("all").alias("lang"), F.col("mean_dist").alias("value")))
    return _union(parts)


WORKLOADS = {
    "wl_main_compare": main_compare, "wl_seed_spread": seed_spread, "wl_capacity_scaling": capacity_scaling, "wl_ablation": ablation, "wl_by_language": by_language, "wl_k_sweep": k_sweep, "wl_landscape": landscape,
    "wl_feature_shape": feature_shape, "wl_efficiency": efficiency, "wl_blend": blend, "wl_decontaminate": decontaminate, "wl_probe_scale": probe_scale, "wl_hyper": hyper, "wl_saturation": saturation,
    "wl_progress_radar": progress_radar, "wl_overhead": overhead, "wl_suite_groups": suite_groups, "wl_error_bound": error_bound,
}
