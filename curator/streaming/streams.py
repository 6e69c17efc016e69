"""Structured Streaming surfaces; each gives what the batch form gives on the same rows."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from curator.functions.workspace import shared_root
from curator.operators import lloyd


def file_stream(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def assign_stream(stream: DataFrame, centres: np.ndarray) -> DataFrame:
    """Stateless: the nearest frozen centre of each arriving sample."""
    return lloyd.assign(stream, centres)


def windows(events: DataFrame, size: str, slide: str | None = None, late: str | None = None) -> DataFrame:
    """Counts and sums of events by tumbling or sliding window and type."""
    src = events.withWatermark("ts", late) if late else events
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return src.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("v")).select(F.col("w.start").alias("start"), "event_type", "n", "v")


def sessions(events: DataFrame, gap: str, late: str | None = None) -> DataFrame:
    """Sessions of a user: events with no gap of that length between them."""
    src = events.withWatermark("ts", late) if late else events
    return src.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "n")


def first_only(events: DataFrame, keys: list[str], late: str) -> DataFrame:
    """One event for each key within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def running_quota(stream: DataFrame) -> DataFrame:
    """(k, n, tokens) so far for each cluster: state is two counters per cluster."""

    def update(key: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, tokens = state.get if state.exists else (0, 0)
        for part in parts:
            n, tokens = n + len(part), tokens + int(part["n_tokens"].sum())
        state.update((n, tokens))
        yield pd.DataFrame({"k": [key[0]], "n": [n], "tokens": [tokens]})

    return stream.groupBy("k").applyInPandasWithState(update, "k int, n long, tokens long", "n long, tokens long", "update", "NoTimeout")


def replay(stream: DataFrame, mode: str = "append", each: Callable[[DataFrame, int], None] | None = None) -> DataFrame:
    """Run a stream over what is there now and return its rows, from a table in the shared folder.

    Batches are written by ``foreachBatch`` under their number, so a batch that is run again overwrites itself;
    with 'complete' or 'update' output the latest rows win at the reader.
    """
    spark = stream.sparkSession
    root = f"{shared_root(spark)}/stream-{uuid.uuid4().hex}"

    def write(df: DataFrame, number: int) -> None:
        df.write.mode("overwrite").parquet(f"{root}/rows/batch={number}")
        if each:
            each(df, number)

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).foreachBatch(write).start()
    query.awaitTermination()
    out = spark.read.schema(f"{', '.join(f'`{f.name}` {f.dataType.simpleString()}' for f in stream.schema.fields)}, batch int").parquet(f"{root}/rows")
    if mode == "complete":
        return out.join(F.broadcast(out.agg(F.max("batch").alias("batch"))), "batch", "left_semi").drop("batch")
    return out if mode == "update" else out.drop("batch")
