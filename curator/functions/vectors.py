"""Vector arithmetic on array columns.

Sums are unrolled over the fixed dimension: whole-stage code instead of interpreted lambdas.  For large dimensions
the Arrow operators (lloyd, embed) are the way.
"""

from __future__ import annotations

from functools import reduce
from operator import add

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

DIM = 64


def dot(a: Column, b: Column, d: int = DIM) -> Column:
    return reduce(add, [a[i] * b[i] for i in range(d)])


def sq_dist(a: Column, b: Column, d: int = DIM) -> Column:
    return reduce(add, [(a[i] - b[i]) * (a[i] - b[i]) for i in range(d)])


def unit(a: Column, d: int = DIM) -> Column:
    """Scaled to length one; a zero vector stays."""
    n = F.sqrt(dot(a, a, d))
    return F.transform(a, lambda x: F.when(n > 0, x / n).otherwise(x))


def centres(df: DataFrame, keys: list[str], d: int = DIM) -> DataFrame:
    """(keys, mu): mean vector of each group, scaled to length one; partial sums before the shuffle."""
    means = df.groupBy(*keys).agg(F.array(*[F.avg(F.col("emb")[i]) for i in range(d)]).alias("m"))
    return means.select(*keys, unit(F.col("m"), d).alias("mu"))


def with_distance(df: DataFrame, mu: DataFrame, keys: list[str], name: str = "dist", d: int = DIM) -> DataFrame:
    """Adds the distance to the group's centre; ``mu`` has a row for each group and is small by contract."""
    return df.join(F.broadcast(mu), keys).withColumn(name, F.sqrt(sq_dist(F.col("emb"), F.col("mu"), d))).drop("mu")
