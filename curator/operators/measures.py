"""What is reported about a subset, and about results as a whole."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from curator.functions.joins import small
from curator.functions.keyed import SEED, draw
from curator.functions.text import n_tokens, words
from curator.functions.workspace import stash

#: Published scores (model, method, epoch, printed average, seven metrics).
METRICS = ("he", "he_plus", "mbpp", "mbpp_plus", "livecode", "crux_in", "crux_out")
PUBLISHED = (
    ("16B", "random", 1.0, 32.92, (55.9, 48.6, 33.5, 37.6, 1.1, 29.8, 24.1)),
    ("16B", "curator", 0.5, 32.31, (49.9, 43.8, 34.6, 40.9, 6.4, 26.0, 24.6)),
    ("16B", "curator", 1.0, 39.50, (59.3, 55.1, 41.8, 47.8, 10.8, 31.6, 30.1)),
    ("8B", "random", 1.0, 29.11, (45.3, 44.1, 30.5, 34.2, 2.0, 22.3, 25.5)),
    ("8B", "rating selector", 1.0, 35.02, (53.2, 49.6, 35.3, 43.5, 4.7, 31.4, 27.7)),
    ("8B", "mixture optimiser", 1.0, 35.21, (52.4, 48.8, 36.7, 45.5, 6.9, 29.7, 26.6)),
    ("8B", "curator", 0.5, 30.02, (47.7, 43.5, 32.4, 42.2, 5.2, 16.6, 22.5)),
    ("8B", "curator", 1.0, 36.44, (53.7, 50.3, 37.4, 46.6, 7.8, 31.0, 28.4)),
    ("8B", "flat random", 1.0, 29.18, (46.0, 44.1, 31.1, 34.6, 1.8, 21.4, 25.2)),
    ("8B", "flat scored", 1.0, 33.00, (51.4, 48.1, 34.5, 40.1, 1.9, 27.0, 28.0)),
    ("8B", "no micro", 1.0, 31.21, (45.8, 43.8, 33.8, 40.1, 2.3, 24.3, 28.3)),
    ("8B", "no macro", 1.0, 34.86, (52.2, 49.5, 36.1, 43.1, 4.5, 31.3, 27.5)),
)
GROUPS = {"generation": ("he", "he_plus", "mbpp", "mbpp_plus"), "reasoning": ("livecode", "crux_in", "crux_out")}


def published(spark: SparkSession) -> DataFrame:
    """(model, method, epoch, printed, metric, value)."""
    rows = [(m, n, e, p, metric, v) for m, n, e, p, vs in PUBLISHED for metric, v in zip(METRICS, vs, strict=True)]
    return spark.createDataFrame(rows, "model string, method string, epoch double, printed double, metric string, value double")


def averages(results: DataFrame, reference: str = "random") -> DataFrame:
    """Unweighted mean of the metrics beside the printed average, and the difference to the reference method (random) of the
    same model: as a number of one decimal and as a label with its sign."""
    avg = results.groupBy("model", "method", "epoch", "printed").agg(F.avg("value").alias("mean"))
    ref = avg.where(F.col("method") == reference).select("model", F.col("mean").alias("ref"))
    return avg.join(F.broadcast(ref), "model").select("model", "method", "epoch", "printed", "mean", (F.round(F.col("mean") - F.col("ref") + 1e-12, 1) + 0.0).alias("delta")).withColumn("sign", F.when(F.col("delta") > 0, "up").when(F.col("delta") < 0, "down").otherwise("same"))


def efficiency(reference: list[tuple[float, float]], method: list[tuple[float, float]]) -> float | None:
    """Budget at which the reference reaches its final value over the smallest at which the method does; None if never.

    Curves are (budget, value); values are made monotone and interpolated.
    """
    ref, other = sorted(reference), sorted(method)
    if not ref or not other:
        return None
    goal = max(v for _, v in ref)
    reach = lambda curve: _reach(curve, goal)
    a, b = reach(ref), reach(other)
    return a / b if a is not None and b else None


def _reach(curve: list[tuple[float, float]], goal: float) -> float | None:
    best, last = -math.inf, None
    for x, y in curve:
        top = max(best, y)
        if top >= goal:
            if last is None or top == best or best == -math.inf:
                return x
            return last + (x - last) * (goal - best) / (top - best)
        best, last = top, x
    return None


def shape(df: DataFrame, columns: list[str]) -> DataFrame:
    """(feature, skew, skew_log, kurt, kurt_log, cv): does the log of a feature look more normal than the feature?"""
    aggs = []
    for c in columns:
        x, y = F.col(c).cast("double"), F.log1p(F.col(c).cast("double"))
        aggs.append(F.struct(F.lit(c).alias("feature"), F.skewness(x).alias("skew"), F.skewness(y).alias("skew_log"), F.kurtosis(x).alias("kurt"), F.kurtosis(y).alias("kurt_log"), (F.stddev_pop(x) / F.avg(x)).alias("cv")))
    return df.agg(F.array(*aggs).alias("a")).select(F.explode("a").alias("x")).select("x.*")


def ks_normal(df: DataFrame, column: str, steps: int = 200) -> DataFrame:
    """Largest gap between the quantiles' levels and the normal fit's, on a grid of quantiles."""
    moments = df.agg(F.avg(column).alias("m"), F.stddev_pop(column).alias("s"), F.percentile_approx(column, [(i + 0.5) / steps for i in range(steps)], 10000).alias("q")).first()
    if not moments["s"]:
        return df.sparkSession.createDataFrame([(column, None)], "feature string, ks double")
    gap = max(abs(0.5 * (1 + math.erf((float(q) - moments["m"]) / moments["s"] / math.sqrt(2))) - (i + 0.5) / steps) for i, q in enumerate(moments["q"]))
    return df.sparkSession.createDataFrame([(column, float(gap))], "feature string, ks double")


def coverage(rows: DataFrame, subset: DataFrame, keys: tuple[str, ...] = ("k",)) -> DataFrame:
    """(covered, tv, entropy): share of cells with a selected row, total variation of cell masses, entropy of the selection's."""
    flags = subset.select("doc_id", F.lit(1).alias("__in"))
    by = rows.select("doc_id", *keys).join(flags, "doc_id", "left").groupBy(*keys).agg(F.count(F.lit(1)).alias("n"), F.count("__in").alias("s"))
    by = by.crossJoin(F.broadcast(by.agg(F.sum("n").alias("all_n"), F.sum("s").alias("all_s"))))
    q = F.col("s") / F.nullif(F.col("all_s"), F.lit(0))
    return by.agg(F.avg((F.col("s") > 0).cast("double")).alias("covered"), (F.sum(F.abs(q - F.col("n") / F.col("all_n"))) / 2).alias("tv"), (-F.sum(F.when(q > 0, q * F.log(q)).otherwise(0.0))).alias("entropy"))


def rejected(rows: DataFrame, subset: DataFrame, dist: str = "dist") -> DataFrame:
    """(kept, mean_dist, far_share): distance to the centre of kept and dropped rows, and how many lie in the farthest tenth."""
    far = rows.agg(F.percentile_approx(dist, 0.9, 10000).alias("far"))
    flagged = rows.join(subset.select("doc_id", F.lit(True).alias("kept")), "doc_id", "left").crossJoin(F.broadcast(far))
    return flagged.groupBy(F.coalesce("kept", F.lit(False)).alias("kept")).agg(F.avg(dist).alias("mean_dist"), F.avg((F.col(dist) >= F.col("far")).cast("double")).alias("far_share"))


def word_bucket(buckets: int):
    """Bucket of the word ``w``: the same number in SQL engines."""
    return (F.conv(F.substring(F.md5(F.col("w").cast("binary")), 1, 8), 16, 10).cast("long") % buckets).cast("int")


def cross_entropy_at(subset_docs: DataFrame, held_out: DataFrame, parts: tuple[float, ...] = (1.0,), buckets: int = 1 << 14, alpha: float = 0.5, by: str = "lang", seed: int = SEED) -> DataFrame:
    """(part, by, value): negative cross-entropy per token of held-out texts under the smoothed hashed-word model of each
    nested part (:func:`sampling.epoch_prefix`) of the subset; all parts out of one scan.

    Words are counted before they are hashed, so md5 is taken once for each distinct word of a task.
    """
    ws = subset_docs.select(draw("doc_id", seed, "epoch").alias("u"), F.explode(words(F.lower("text"))).alias("w"))
    level = F.lit(len(parts) - 1)
    for i in range(len(parts) - 2, -1, -1):
        level = F.when(F.col("u") < sorted(parts)[i], F.lit(i)).otherwise(level)
    inside = ws.where(F.col("u") < max(parts)).groupBy(level.alias("level"), "w").agg(F.count(F.lit(1)).alias("c"))
    taken = [F.sum(F.when(F.col("level") <= sorted(parts).index(p), F.col("c")).otherwise(0)).alias(f"c{i}") for i, p in enumerate(parts)]
    model = inside.groupBy(word_bucket(buckets).alias("bucket")).agg(*taken)
    total = model.agg(*[F.coalesce(F.sum(f"c{i}"), F.lit(0)).alias(f"N{i}") for i in range(len(parts))])
    seen = held_out.select(by, F.explode(words(F.lower("text"))).alias("w")).groupBy(by, "w").agg(F.count(F.lit(1)).alias("t")).groupBy(by, word_bucket(buckets).alias("bucket")).agg(F.sum("t").alias("t"))
    joined = seen.join(model, "bucket", "left").crossJoin(F.broadcast(total))
    logp = lambda i: F.log((F.coalesce(f"c{i}", F.lit(0)) + alpha) / (F.col(f"N{i}") + alpha * buckets))
    values = joined.groupBy(by).agg(F.array(*[F.struct(F.lit(float(p)).alias("part"), (F.sum(F.col("t") * logp(i)) / F.sum("t")).alias("value")) for i, p in enumerate(parts)]).alias("v"))
    return values.select(F.explode("v").alias("v"), by).select("v.part", by, "v.value")


def cross_entropy(subset_docs: DataFrame, held_out: DataFrame, buckets: int = 1 << 14, alpha: float = 0.5, by: str = "lang") -> DataFrame:
    """(by, value): the same for the whole subset."""
    return cross_entropy_at(subset_docs, held_out, (1.0,), buckets, alpha, by).select(by, "value")


#: Subsets that one table of members can tell apart.
MOST = 62


def members(subsets: list[DataFrame]) -> DataFrame:
    """(doc_id, bits), written: the subsets that have a document, the first as the lowest bit."""
    if len(subsets) > MOST:
        raise ValueError(f"at most {MOST} subsets share a scan")
    rows = None
    for i, s in enumerate(subsets):
        part = s.select("doc_id", F.lit(1 << i).cast("long").alias("bits"))
        rows = part if rows is None else rows.unionAll(part)
    return stash(rows.groupBy("doc_id").agg(F.bit_or("bits").alias("bits")), "members")


def _has(i: int) -> Column:
    return F.col("bits").bitwiseAND(F.lit(1 << i)) != 0


def _each(df: DataFrame, columns: list[Column], name: str, *keys: str) -> DataFrame:
    """(i, keys, name): a row for each subset."""
    return df.select(*keys, F.posexplode(F.array(*columns)).alias("i", name))


def cross_entropies(docs: DataFrame, owners: DataFrame, n: int, held_out: DataFrame, buckets: tuple[int, ...] = (1 << 14,), alpha: float = 0.5, by: str = "lang") -> DataFrame:
    """(buckets, i, by, value): :func:`cross_entropy` of each of the ``n`` subsets of ``owners``, all out of one scan."""
    ws = docs.select("doc_id", "text").join(small(owners, 24), "doc_id").select("bits", F.explode(words(F.lower("text"))).alias("w"))
    counts = [f"c{i}" for i in range(n)]
    inside = ws.groupBy("w").agg(*[F.sum(_has(i).cast("long")).alias(f"c{i}") for i in range(n)])
    seen = held_out.select(by, F.explode(words(F.lower("text"))).alias("w")).groupBy(by, "w").agg(F.count(F.lit(1)).alias("t"))
    if len(buckets) > 1:
        inside, seen = stash(inside, "words"), stash(seen, "held-words")
    out = None
    for b in buckets:
        model = stash(inside.groupBy(word_bucket(b).alias("bucket")).agg(*[F.sum(c).alias(c) for c in counts]), "model")
        total = model.agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(f"N{c}") for c in counts])
        joined = seen.groupBy(by, word_bucket(b).alias("bucket")).agg(F.sum("t").alias("t")).join(model, "bucket", "left").crossJoin(F.broadcast(total))
        logp = lambda c: F.log((F.coalesce(c, F.lit(0)) + alpha) / (F.col(f"N{c}") + alpha * b))  # noqa: B023, E731
        values = joined.groupBy(by).agg(F.sum("t").alias("t"), *[F.sum(F.col("t") * logp(c)).alias(c) for c in counts])
        part = _each(values, [F.col(c) / F.col("t") for c in counts], "value", by).select(F.lit(b).alias("buckets"), "i", by, "value")
        out = part if out is None else out.unionByName(part)
    return out


def cross_entropy_curves(docs: DataFrame, owners: DataFrame, n: int, held_out: DataFrame, parts: tuple[float, ...], buckets: int = 1 << 14, alpha: float = 0.5, by: str = "lang", seed: int = SEED) -> DataFrame:
    """(i, part, by, value): :func:`cross_entropy_at` of each of the ``n`` subsets of ``owners``, all out of one scan."""
    levels = sorted(parts)
    ws = docs.select("doc_id", "text").join(small(owners, 24), "doc_id").select("bits", draw("doc_id", seed, "epoch").alias("u"), F.explode(words(F.lower("text"))).alias("w"))
    level = F.lit(len(levels) - 1)
    for j in range(len(levels) - 2, -1, -1):
        level = F.when(F.col("u") < levels[j], F.lit(j)).otherwise(level)
    inside = ws.where(F.col("u") < levels[-1]).groupBy(level.alias("level"), "w").agg(*[F.sum(_has(i).cast("long")).alias(f"c{i}") for i in range(n)])
    cells = [(i, j, f"c{i}_{j}") for i in range(n) for j in range(len(levels))]
    model = stash(inside.groupBy(word_bucket(buckets).alias("bucket")).agg(*[F.sum(F.when(F.col("level") <= j, F.col(f"c{i}")).otherwise(0)).alias(c) for i, j, c in cells]), "model")
    total = model.agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(f"N{c}") for _, _, c in cells])
    seen = held_out.select(by, F.explode(words(F.lower("text"))).alias("w")).groupBy(by, "w").agg(F.count(F.lit(1)).alias("t")).groupBy(by, word_bucket(buckets).alias("bucket")).agg(F.sum("t").alias("t"))
    joined = seen.join(model, "bucket", "left").crossJoin(F.broadcast(total))
    logp = lambda c: F.log((F.coalesce(c, F.lit(0)) + alpha) / (F.col(f"N{c}") + alpha * buckets))
    values = joined.groupBy(by).agg(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(float(levels[j])).alias("part"), (F.sum(F.col("t") * logp(c)) / F.sum("t")).alias("value")) for i, j, c in cells]).alias("v"))
    return values.select(F.explode("v").alias("v"), by).select("v.i", "v.part", by, "v.value")


def qualities(labels: DataFrame, owners: DataFrame, n: int) -> DataFrame:
    """(i, value): mean of quality x (1 - toxic) over the labelled documents of each subset."""
    rows = labels.join(owners, "doc_id")
    return _each(rows.agg(*[F.avg(F.when(_has(i), F.col("quality") * (1 - F.col("toxic")))).alias(f"q{i}") for i in range(n)]), [F.col(f"q{i}") for i in range(n)], "value")


def coverages(rows: DataFrame, owners: DataFrame, n: int, keys: tuple[str, ...] = ("k",)) -> DataFrame:
    """(i, covered, tv, entropy): :func:`coverage` of each subset, out of one scan."""
    marked = rows.select("doc_id", *keys).join(owners, "doc_id", "left")
    by = marked.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"), *[F.count(F.when(_has(i), 1)).alias(f"s{i}") for i in range(n)])
    by = _each(by, [F.col(f"s{i}") for i in range(n)], "s", *keys, "n")
    by = by.join(F.broadcast(by.groupBy("i").agg(F.sum("n").alias("all_n"), F.sum("s").alias("all_s"))), "i")
    q = F.col("s") / F.nullif(F.col("all_s"), F.lit(0))
    return by.groupBy("i").agg(F.avg((F.col("s") > 0).cast("double")).alias("covered"), (F.sum(F.abs(q - F.col("n") / F.col("all_n"))) / 2).alias("tv"), (-F.sum(F.when(q > 0, q * F.log(q)).otherwise(0.0))).alias("entropy"))


def token_shares(docs: DataFrame, owners: DataFrame, n: int, by: str = "lang") -> DataFrame:
    """(i, by, value): tokens of each subset by language or source, out of one scan."""
    rows = docs.select("doc_id", by, "text").join(small(owners, 24), "doc_id").select(by, "bits", n_tokens("text").alias("t"))
    sums = rows.groupBy(by).agg(*[F.struct(F.count(F.when(_has(i), 1)).alias("n"), F.sum(F.when(_has(i), F.col("t"))).cast("double").alias("value")).alias(f"x{i}") for i in range(n)])
    return _each(sums, [F.col(f"x{i}") for i in range(n)], "x", by).where("x.n > 0").select("i", by, "x.value")
