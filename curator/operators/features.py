"""Four features of a cluster, on the scale that suits each: tightness and entropy raw, size and length in logs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

DELTA = 1e-3
FEATURES = ("coh", "size", "len", "ent")


def cluster_features(df: DataFrame, keys: list[str], dist: str = "dist", delta: float = DELTA, form: str = "inverse") -> DataFrame:
    """(keys, n, z_coh, z_size, z_len, z_ent) from rows with dist, n_tokens and lang.

    One shuffle of a row per group, language and task; entropy is ln n - sum(n_l ln n_l) / n.  ``form``: 'inverse'
    (1 / (delta + mean distance)) or 'one_plus' (1 / (1 + mean distance)).
    """
    by_lang = df.groupBy(*keys, "lang").agg(F.count(F.lit(1)).alias("nl"), F.sum(dist).alias("sd"), F.sum("n_tokens").alias("st"))
    n = F.sum("nl")
    mean = F.sum("sd") / n
    coh = 1 / (F.lit(delta) + mean) if form == "inverse" else 1 / (1 + mean)
    ent = F.greatest(F.log(n.cast("double")) - F.sum(F.col("nl") * F.log(F.col("nl").cast("double"))) / n, F.lit(0.0))
    grouped = by_lang.groupBy(*keys) if keys else by_lang.groupBy()
    return grouped.agg(n.alias("n"), coh.alias("z_coh"), F.log1p(n.cast("double")).alias("z_size"), F.log1p(F.sum("st") / n).alias("z_len"), ent.alias("z_ent"))


def levels(df: DataFrame, dist: str = "dist_sub", parent_dist: str = "dist") -> DataFrame:
    """Child, parent and global features in one table: gid 0 for (k, j), 1 for k, 3 for all."""
    child = cluster_features(df, ["k", "j"], dist).withColumn("gid", F.lit(0))
    parent = cluster_features(df, ["k"], parent_dist).withColumns({"gid": F.lit(1), "j": F.lit(None).cast("int")})
    whole = cluster_features(df, [], parent_dist).withColumns({"gid": F.lit(3), "k": F.lit(None).cast("int"), "j": F.lit(None).cast("int")})
    return child.unionByName(parent).unionByName(whole)


def znorm(feats: DataFrame, names: tuple[str, ...] = FEATURES, ddof: int = 0) -> DataFrame:
    """Adds zn_* (population moments over all rows by default); a constant feature gives 0."""
    sd = F.stddev_pop if ddof == 0 else F.stddev_samp
    moments = feats.agg(*[f(f"z_{n}").alias(f"{p}_{n}") for n in names for p, f in (("m", F.avg), ("s", sd))])
    out = feats.crossJoin(F.broadcast(moments))
    for n in names:
        flat_ = F.coalesce(F.col(f"s_{n}"), F.lit(0.0)) < 1e-12
        out = out.withColumn(f"zn_{n}", F.when(flat_, F.lit(0.0)).otherwise((F.col(f"z_{n}") - F.col(f"m_{n}")) / F.when(flat_, F.lit(1.0)).otherwise(F.col(f"s_{n}"))))
    return out.drop(*moments.columns)
