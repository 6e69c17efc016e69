"""Training-data pipeline over ``documents``: stages in order, each written as Parquet and read again."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from curator.functions.workspace import stash
from curator.llm.contamination import contaminated_words
from curator.llm.lines import without_repeated_lines
from curator.llm.near import near_groups
from curator.llm.pieces import encode_decode
from curator.llm.rows import attached
from curator.llm.toxicity import clean_documents


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity model doesn't reject."""
    return clean_documents(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later documents lose the line blocks that an earlier one has; those that lose all of their text go."""
    return without_repeated_lines(docs)


def keep_one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The smallest doc_id of each near-duplicate group (five-word shingles, similarity of 0.8 or more), in one row."""
    rows, base = attached(docs)
    others = near_groups(base, k=5, percent=80).where(~F.col("kept")).select(F.col("key").alias("__key"))
    kept = rows.join(others, "__key", "left_anti")
    n, keys = rows.agg(F.count(F.lit(1)), F.count_distinct("__key")).first()
    kept = kept.dropDuplicates(["__key"]) if keys < n else kept
    return kept.select(docs.columns)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of which benchmark windows cover less than a twentieth."""
    rows, base = attached(docs)
    found = contaminated_words(base, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    bad = found.where("n_hit > 0 and 20 * n_hit >= n_words").select(F.col("key").alias("__key"))
    return rows.join(bad, "__key", "left_anti").select(docs.columns)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each document and the digests of ids and decoded text."""
    coded = encode_decode(docs)
    return coded.select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "ids")


STAGES = [
    ("toxicity", drop_toxic),
    ("line dedup", drop_repeated_lines),
    ("near dedup", keep_one_of_each_group),
    ("decontamination", drop_contaminated),
    ("encode and decode", encode),
]

#: Model scores, MinHash and BPE have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each stage's result is a written table."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = stash(docs, name.replace(" ", "-"))
    return docs.select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256", F.size("ids").alias("n_ids"))
