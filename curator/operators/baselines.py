"""The methods that the curator is compared with."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from curator.functions.keyed import SEED, draw
from curator.functions.text import n_tokens, words
from curator.functions.workspace import stash

Raters = dict[str, Column]


def random(docs: DataFrame, share: float, seed: int = SEED) -> DataFrame:
    """Uniform over the corpus: a keyed threshold, map-only."""
    return docs.where(draw("doc_id", seed, "random") < share)


def default_raters(text: str = "text") -> Raters:
    """Four ratings of a document in [0, 1]: readability, cleanliness, completeness, reasoning words."""
    t = F.col(text)
    ws = words(F.lower(t))
    n = F.greatest(F.size(ws), F.lit(1))
    size = F.greatest(F.length(t), F.lit(1))
    lines = F.split(t, "\n")
    connect = F.array(*[F.lit(w) for w in ("because", "therefore", "since", "if", "then", "that", "daher", "weil", "dass", "donc", "car", "que", "porque", "si", "und", "and", "et", "y")])
    return {
        "readable": F.exp(-F.pow((size / n - 6.5) / 3, F.lit(2.0))),
        "clean": F.length(F.regexp_replace(t, r"[^\p{L}\s.,;:'-]", "")) / size * (F.size(F.array_distinct(lines)) / F.greatest(F.size(lines), F.lit(1))),
        "complete": F.least(F.lit(1.0), n / 200) * F.when(F.trim(t).rlike(r"[.!?]$"), 1.0).otherwise(0.6),
        "reasoning": F.least(F.lit(1.0), 8 * F.size(F.filter(ws, lambda w: F.array_contains(connect, w))) / n),
    }


def code_raters(raters: Raters, text: str = "text") -> Raters:
    """The adapter to program text: reasoning words and sentence ends make way for nesting, layout and symbols."""
    t = F.col(text)
    count = lambda pattern: F.regexp_count(t, F.lit(pattern))
    opened, closed = count(r"[(\[{]"), count(r"[)\]}]")
    lines = F.size(F.split(t, "\n"))
    own = {
        "balanced": 1 - F.abs(opened - closed) / F.greatest(opened + closed, F.lit(1)),
        "laid_out": count(r"(?m)^[ \t]+[^ \t\n]") / F.greatest(lines, F.lit(1)),
        "symbols": F.least(F.lit(1.0), 20 * count(r"[(){};=<>]") / F.greatest(F.length(t), F.lit(1))),
    }
    return {n: c for n, c in raters.items() if n not in ("reasoning", "complete")} | own


def rated(docs: DataFrame, raters: Raters | None = None, weights: dict[str, float] | None = None, labels: DataFrame | None = None, adapter: Callable[[Raters], Raters] | None = None) -> DataFrame:
    """(doc_id, n_tokens, ratings, rating).  Weights: equal, given, or a logistic fit on quality x (1 - toxic)."""
    raters = raters or default_raters()
    raters = adapter(raters) if adapter else raters
    names = list(raters)
    # written once: the ratings are read for the fit, the histogram and both parts of the selection
    out = stash(docs.select("doc_id", n_tokens("text").alias("n_tokens"), *[F.coalesce(raters[n], F.lit(0.0)).cast("double").alias(n) for n in names]), "ratings")
    if labels is not None:
        from pyspark.ml.classification import LogisticRegression
        from pyspark.ml.functions import array_to_vector

        y = labels.select("doc_id", (F.col("quality") * (1 - F.col("toxic"))).cast("double").alias("y"))
        train = out.join(y, "doc_id").select(array_to_vector(F.array(*names)).alias("features"), "y")
        model = LogisticRegression(labelCol="y", maxIter=30, regParam=1e-3).fit(train)
        z = F.lit(float(model.intercept))
        for n, c in zip(names, model.coefficients.toArray().tolist(), strict=True):
            z = z + F.lit(c) * F.col(n)
        return out.withColumn("rating", 1 / (1 + F.exp(-z)))
    weights = weights or dict.fromkeys(names, 1.0)
    total = sum(weights.values())
    return out.withColumn("rating", sum((F.lit(weights[n] / total) * F.col(n) for n in names), F.lit(0.0)))


def rating_selector(scored: DataFrame, tokens: float, steps: int = 1000) -> DataFrame:
    """The best rated documents up to a token budget.

    A histogram of tokens by rating gives the bin in which the budget ends; only that bin is ordered, by ranges of (rating,
    id), each with its running sum after the sums of those before, so equal ratings of very many documents are no task's load.
    """
    bin_ = F.least(F.floor(F.col("rating") * steps), F.lit(steps - 1)).cast("int")
    filled, cut = 0.0, -1
    for row in sorted(scored.groupBy(bin_.alias("b")).agg(F.sum("n_tokens").alias("t")).collect(), key=lambda r: -r["b"]):
        if filled + row["t"] > tokens:
            cut = row["b"]
            break
        filled += row["t"]
    sure = scored.where(bin_ > cut)
    if cut < 0:
        return sure
    ranges = scored.where(bin_ == cut).repartitionByRange(F.desc("rating"), "doc_id").withColumn("__range", F.spark_partition_id())
    ranges = stash(ranges, "edge")
    before, begins = 0.0, []
    for row in sorted(ranges.groupBy("__range").agg(F.sum("n_tokens").alias("t")).collect(), key=lambda r: r["__range"]):  # a row per partition
        begins.append((row["__range"], before))
        before += row["t"]
    begins = scored.sparkSession.createDataFrame(begins, "__range int, __before double")
    w = Window.partitionBy("__range").orderBy(F.desc("rating"), "doc_id").rowsBetween(Window.unboundedPreceding, 0)
    edge = ranges.withColumn("__run", F.sum("n_tokens").over(w)).join(F.broadcast(begins), "__range")
    return sure.unionByName(edge.where(F.col("__before") + F.col("__run") <= tokens - filled).select(scored.columns))


def flat_mix(docs: DataFrame, budget_docs: float, kind: str = "natural", domain: str = "source", temperature: float = 2.0, seed: int = SEED) -> DataFrame:
    """Flat domain proportions: natural, uniform, or natural to the power 1/temperature; uniform within a domain."""
    sizes = docs.groupBy(domain).agg(F.count(F.lit(1)).alias("n"))
    weight = {"natural": F.col("n").cast("double"), "uniform": F.lit(1.0), "temperature": F.pow(F.col("n").cast("double"), F.lit(1 / temperature))}[kind]
    w = sizes.withColumn("w", weight)
    share = w.crossJoin(F.broadcast(w.agg(F.sum("w").alias("all")))).select(domain, F.least(F.lit(1.0), F.lit(float(budget_docs)) * F.col("w") / F.col("all") / F.col("n")).alias("__share"))
    return docs.join(F.broadcast(share), domain).where(draw("doc_id", seed, "mix") < F.col("__share")).drop("__share")


def domain_counts(docs: DataFrame, domain: str = "source", buckets: int = 4096) -> DataFrame:
    """(domain, bucket, c): hashed word counts of each domain; counts of a mixture are linear in its shares."""
    ws = docs.select(domain, F.explode(words(F.lower("text"))).alias("w"))
    return ws.groupBy(domain, F.pmod(F.xxhash64("w"), F.lit(buckets)).cast("int").alias("bucket")).agg(F.count(F.lit(1)).alias("c"))


Counted = tuple[list, np.ndarray, np.ndarray]


def counted(docs: DataFrame, held_out: DataFrame, domain: str = "source", buckets: int = 4096) -> Counted:
    """(domains, their word counts by bucket, held-out word counts by bucket): what a mixture is valued by, whatever the seed."""
    rows = domain_counts(docs, domain, buckets).collect()  # domains x buckets
    names = sorted({r[domain] for r in rows})
    at = {d: i for i, d in enumerate(names)}
    counts = np.zeros((len(names), buckets))
    for r in rows:
        counts[at[r[domain]], r["bucket"]] = r["c"]
    held = np.zeros(buckets)
    for r in domain_counts(held_out.withColumn("__all", F.lit("all")), "__all", buckets).collect():
        held[r["bucket"]] = r["c"]
    return names, counts, held


def mixture_optimiser(docs: DataFrame, held_out: DataFrame, domain: str = "source", rounds: int = 3, candidates: int = 64, buckets: int = 4096, seed: int = SEED, adapter: Callable[[np.ndarray], np.ndarray] | None = None, given: Counted | None = None) -> tuple[dict, list[dict]]:
    """Shares of the best mixture found, and every candidate's value.

    Candidates are drawn around natural shares; each is valued by the held-out cross-entropy of the mixture's smoothed
    word distribution (from per-domain counts: no pass over the corpus), a ridge regression on shares and their logs
    ranks fresh draws, and the next round draws around the best quarter.  It needs held-out data and a proxy, which
    the curator does not.  ``given``: what :func:`counted` made of the same documents.
    """
    names, counts, held = given or counted(docs, held_out, domain, buckets)
    held = held / max(held.sum(), 1)
    natural = counts.sum(1) / counts.sum()
    dist = counts / np.maximum(counts.sum(1, keepdims=True), 1)
    rng = np.random.default_rng(seed)

    def value(shares: np.ndarray) -> float:
        p = (shares @ dist + 1e-6) / (1 + buckets * 1e-6)
        v = float(held @ np.log(p))
        return float(adapter(np.array([v]))[0]) if adapter else v

    seen: list[dict] = [{"round": 0, "shares": natural, "value": value(natural)}]
    centre, spread = [natural], 20.0
    basis = lambda s: np.concatenate([s, np.log(s + 1e-4), [1.0]])
    for step in range(1, rounds + 1):
        drawn = np.array([rng.dirichlet(centre[i % len(centre)] * spread + 0.05) for i in range(candidates * 4)])
        if step > 1:
            x = np.array([basis(c["shares"]) for c in seen])
            y = np.array([c["value"] for c in seen])
            coef = np.linalg.solve(x.T @ x + 1e-3 * np.eye(x.shape[1]), x.T @ y)
            drawn = drawn[np.argsort(-(np.array([basis(s) for s in drawn]) @ coef), kind="stable")]
        seen += [{"round": step, "shares": s, "value": value(s)} for s in drawn[:candidates]]
        best = sorted(seen, key=lambda c: -c["value"])[: max(1, candidates // 4)]
        centre, spread = [c["shares"] for c in best], spread * 2
    top = max(seen, key=lambda c: c["value"])
    return dict(zip(names, top["shares"].tolist(), strict=True)), seen


def by_shares(docs: DataFrame, shares: dict, budget_docs: float, domain: str = "source", seed: int = SEED) -> DataFrame:
    """Documents drawn at given domain shares, uniform within a domain; a domain gives at most all it has."""
    spark = docs.sparkSession
    table = spark.createDataFrame([(d, float(s)) for d, s in shares.items()], f"`{domain}` {docs.schema[domain].dataType.simpleString()}, s double")
    sizes = docs.groupBy(domain).agg(F.count(F.lit(1)).alias("n")).join(F.broadcast(table), domain)
    share = sizes.select(domain, F.least(F.lit(1.0), F.lit(float(budget_docs)) * F.col("s") / F.col("n")).alias("__share"))
    return docs.join(F.broadcast(share), domain).where(draw("doc_id", seed, "mix") < F.col("__share")).drop("__share")


def rules(docs: DataFrame) -> DataFrame:
    """Independent per-document rules: length band, symbols, repeated lines, word length."""
    s = default_raters()
    n = n_tokens("text")
    return docs.where((n >= 20) & (n <= 20_000) & (s["clean"] >= 0.5) & (s["readable"] >= 0.2))
