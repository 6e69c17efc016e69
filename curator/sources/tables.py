"""The given tables, the corpora built from them, and partitioned sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from curator.functions.text import n_tokens

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")

DOCUMENTS = T.StructType([T.StructField(n, t) for n, t in (("doc_id", T.LongType()), ("text", T.StringType()), ("lang", T.StringType()), ("source", T.StringType()), ("n_chars", T.LongType()))])
FEATURES = T.StructType([T.StructField(n, t) for n, t in (("doc_id", T.LongType()), ("lang", T.StringType()), ("source", T.StringType()), ("n_tokens", T.LongType()), ("emb", T.ArrayType(T.DoubleType())))])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def validated(df: DataFrame, schema: T.StructType) -> DataFrame:
    """``df`` with exactly the declared columns; a missing or differently typed one is an error, not a cast."""
    have = {f.name: f.dataType for f in df.schema.fields}
    wrong = [f"{f.name}: {have.get(f.name)} instead of {f.dataType}" for f in schema.fields if have.get(f.name) != f.dataType]
    if wrong:
        raise ValueError("; ".join(wrong))
    return df.select(schema.fieldNames())


def corpus_vec(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents with a given vector: doc_id, lang, source, n_tokens, emb, k (the vector's label)."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "lang", "source", n_tokens("text").alias("n_tokens"))
    vecs = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("doc_id"), F.col("embedding").cast("array<double>").alias("emb"), F.col("label").alias("k"))
    return docs.join(vecs, "doc_id")


def register(spark: SparkSession, sf_dir: str) -> None:
    """All tables as temp views."""
    for name in TABLES:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def write_partitioned(df: DataFrame, path: str, by: str = "k", rows_per_file: int = 1_000_000) -> None:
    """Parquet partitioned by a low-cardinality key; hot keys are split over files by Spark's rebalancing."""
    df.hint("rebalance", by).write.mode("overwrite").option("maxRecordsPerFile", rows_per_file).partitionBy(by).parquet(path)


def write_small(df: DataFrame, path: str, kind: str = "json") -> None:
    """One file of a cluster-sized table."""
    df.coalesce(1).write.mode("overwrite").format(kind).save(path)
