"""Row keys and inputs shared by the text operators."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from curator.functions.workspace import stash


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def keyed(docs: DataFrame) -> tuple[DataFrame, DataFrame | None]:
    """(key, text) with one row per document, and the rows behind it where keys are not doc_ids.

    The key orders as doc_id does.  Where every doc_id is there and stands once, it is the key.  Otherwise
    rows with equal doc_id and text are one document, null ids come first, and rows that share a doc_id but
    not the text rank by the text's hash; the second frame then maps (doc_id, text) to the key.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    n, ids, distinct = docs.agg(F.count(F.lit(1)), F.count("doc_id"), F.count_distinct("doc_id")).first()
    if n == ids == distinct:
        return docs.select(F.col("doc_id").alias("key"), "text"), None
    mark = F.sha2(F.coalesce("text", F.lit("")), 256)
    one = docs.select("doc_id", mark.alias("mark"), F.col("text").isNull().alias("absent")).distinct()
    ranked = stash(one.orderBy(F.col("doc_id").asc_nulls_first(), "mark", "absent").withColumn("key", F.monotonically_increasing_id()), "keys")
    d = docs.alias("d")
    on = F.col("d.doc_id").eqNullSafe(F.col("k.doc_id")) & (F.sha2(F.coalesce("d.text", F.lit("")), 256) == F.col("k.mark")) & (F.col("d.text").isNull() == F.col("k.absent"))
    rows = stash(d.join(ranked.alias("k"), on).select("d.doc_id", "d.text", "k.key"), "keyed")
    return rows.dropDuplicates(["key"]).select("key", "text"), rows


def per_row(result: DataFrame, rows: DataFrame | None) -> DataFrame:
    """Results by key as results by doc_id, one for each input row."""
    if rows is None:
        return result.withColumnRenamed("key", "doc_id")
    cols = [c for c in result.columns if c != "key"]
    return rows.select("doc_id", "key").join(result, "key").select("doc_id", *cols)


def attached(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The documents with all their columns and ``__key``, and (key, text) with one row per document."""
    base, rows = keyed(docs)
    if rows is None:
        return docs.withColumn("__key", F.col("doc_id").cast("long")), base
    known = rows.dropDuplicates(["key"]).select(F.col("doc_id").alias("__id"), F.col("text").alias("__text"), F.col("key").alias("__key"))
    same = F.col("doc_id").cast("long").eqNullSafe(F.col("__id")) & F.col("text").cast("string").eqNullSafe(F.col("__text"))
    return docs.join(known, same).drop("__id", "__text"), base
