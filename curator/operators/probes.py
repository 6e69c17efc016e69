"""A few central samples of each sub-cluster, and the semantic score that they give it."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from curator.functions.text import words


def select(sub: DataFrame, m: int = 3, dist: str = "dist_sub", keys: tuple[str, ...] = ("k", "j")) -> DataFrame:
    """The m members nearest to the centre, ties by id; Spark prunes each task to m rows per group before it shuffles."""
    w = Window.partitionBy(*keys).orderBy(F.col(dist), "doc_id")
    return sub.select(*keys, "doc_id", dist).withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= m)


def score_labels(probe: DataFrame, labels: DataFrame, prior: float = 2.0, keys: tuple[str, ...] = ("k", "j")) -> DataFrame:
    """Mean of quality x (1 - toxic) over labelled probes, drawn towards the corpus rate by ``prior`` pseudo-probes."""
    good = labels.select("doc_id", (F.col("quality") * (1 - F.col("toxic"))).cast("double").alias("good"))
    rate = good.agg(F.avg("good").alias("rate"))
    got = probe.join(good, "doc_id", "left").groupBy(*keys).agg(F.sum("good").alias("s"), F.count("good").alias("c"))
    return got.crossJoin(F.broadcast(rate)).select(*keys, ((F.coalesce("s", F.lit(0.0)) + F.lit(prior) * F.col("rate")) / (F.col("c") + F.lit(prior))).alias("p"))


def text_signals(text: str = "text") -> dict[str, Column]:
    """Signals in [0, 1] of one text: clean characters, few repeated lines, plain word lengths, a workable size."""
    t = F.col(text)
    n = F.greatest(F.length(t), F.lit(1))
    letters = F.length(F.regexp_replace(t, r"[^\p{L}\s]", "")) / n
    lines = F.filter(F.split(t, "\n"), lambda x: F.length(F.trim(x)) > 0)
    fresh = F.size(F.array_distinct(lines)) / F.greatest(F.size(lines), F.lit(1))
    count = F.greatest(F.size(words(t)), F.lit(1))
    mean_len = n / count
    return {
        "clean": letters,
        "fresh": fresh,
        "readable": F.exp(-F.pow((mean_len - 6.5) / 3, F.lit(2.0))),
        "sized": F.least(F.lit(1.0), F.log1p(count.cast("double")) / F.log1p(F.lit(100.0))),
    }


def score_heuristic(probe: DataFrame, docs: DataFrame, keys: tuple[str, ...] = ("k", "j")) -> DataFrame:
    """Mean of the text signals over the probes; fetches the texts of probes only."""
    signals = text_signals()
    value = sum(signals.values(), F.lit(0.0)) / len(signals)
    return probe.join(docs.select("doc_id", "text"), "doc_id").select(*keys, value.alias("v")).groupBy(*keys).agg(F.avg("v").alias("p"))


def score_with(probe: DataFrame, docs: DataFrame, load: Callable[[], Callable[[list[str]], list[float]]], keys: tuple[str, ...] = ("k", "j"), batch: int = 32) -> DataFrame:
    """A user's grader, called for probes only; persist the result, a grader may not answer twice alike."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        grade = load()
        for whole in batches:
            for a in range(0, whole.num_rows, batch):
                part = whole.slice(a, batch)
                values = [float(v) for v in grade([t or "" for t in part.column(len(keys)).to_pylist()])]
                yield pa.RecordBatch.from_arrays([*part.columns[: len(keys)], pa.array(values, pa.float64())], names=[*keys, "v"])

    rows = probe.join(docs.select("doc_id", "text"), "doc_id").select(*keys, "text")
    fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in rows.schema.fields[: len(keys)])
    return rows.mapInArrow(run, f"{fields}, v double").groupBy(*keys).agg(F.avg("v").alias("p"))


def saturation(weights: DataFrame, bins: int = 10, eps: float = 0.02) -> DataFrame:
    """How many sub-clusters share the top score, and the histogram's entropy, before and after the penalty factor."""
    parts = None
    for stage, value in (("before", F.col("p")), ("after", F.col("p") * F.col("penalty_factor"))):
        v = weights.select(value.alias("v"))
        top = v.agg(F.max("v").alias("top"), F.count(F.lit(1)).alias("n"))
        binned = v.crossJoin(F.broadcast(top)).select("n", (F.col("v") >= F.col("top") - eps).cast("int").alias("near"), F.least(F.floor(F.col("v") * bins), F.lit(bins - 1)).alias("bin"))
        counts = binned.groupBy("bin", "n").agg(F.count(F.lit(1)).alias("c"), F.sum("near").alias("near"))
        one = counts.groupBy("n").agg((F.sum("near") / F.col("n")).alias("top_share"), (-F.sum(F.col("c") / F.col("n") * F.log(F.col("c") / F.col("n")))).alias("entropy")).select(F.lit(stage).alias("stage"), "top_share", "entropy")
        parts = one if parts is None else parts.unionByName(one)
    return parts
