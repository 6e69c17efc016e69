"""Connected components over an edge table, by alternating star contraction.

Every round sends each vertex's neighbours to the smallest of them, first for larger neighbours and then for
smaller ones.  Only minima travel (with map-side combining), so a vertex with very many edges costs no more
than its edges' share.  Rounds are written tables; nothing but a count reaches the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from curator.functions.workspace import release, stash


def _large(edges: DataFrame) -> DataFrame:
    both = edges.unionAll(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
    return both.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b")


def _small(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = down.groupBy("a").agg(F.min("b").alias("m"))
    kept = down.join(least, "a")
    return kept.where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).unionAll(least.select("a", F.col("m").alias("b")))


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(a, b) links -> (key, component): the smallest key that each linked key reaches.

    Keys without a link have no row.  Nulls, loops and repeated links don't matter.
    """
    now = stash(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "links")
    for _ in range(rounds):
        # settled: every vertex points at one other, and none of those points on
        n, heads = now.count(), now.select("a").distinct().count()
        if n == heads and now.select(F.col("b").alias("a")).distinct().join(now, "a", "left_semi").isEmpty():
            break
        big = stash(_large(now).distinct(), "links")
        new = stash(_small(big).distinct(), "links")
        release(now)
        release(big)
        now = new
    else:
        raise RuntimeError("components did not settle")
    return now.select(F.col("a").alias("key"), F.col("b").alias("component")).unionAll(now.select(F.col("b").alias("key"), F.col("b").alias("component")).distinct())
