"""The SQL surface: views over the tables and functions for use in ``spark.sql``."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from curator.sources.tables import corpus_vec, register


@pandas_udf(T.DoubleType())
def vec_dot(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([float((x * y).sum()) for x, y in zip(a, b, strict=True)])


@pandas_udf(T.DoubleType())
def entropy_of(c: pd.Series) -> float:
    """Shannon entropy of the values of a group (small groups; cluster_features does it for large ones)."""
    import numpy as np

    q = c.value_counts(normalize=True).to_numpy()
    return float(-(q * np.log(q)).sum()) + 0.0


@udtf(returnType=T.StructType([T.StructField("position", T.IntegerType()), T.StructField("shingle", T.StringType())]))
class Shingles:
    """n-word shingles of a text as rows."""

    def eval(self, text: str, n: int):
        words = (text or "").split()
        for i in range(max(1, len(words) - n + 1) if words else 0):
            yield i, " ".join(words[i : i + n])


def install(spark: SparkSession, sf_dir: str) -> None:
    """Temp views of all tables and of the corpus, and the functions by name."""
    register(spark, sf_dir)
    corpus_vec(spark, sf_dir).createOrReplaceTempView("corpus")
    spark.udf.register("vec_dot", vec_dot)
    spark.udf.register("entropy_of", entropy_of)
    spark.udtf.register("shingles", Shingles)


def mix_of(spark: SparkSession, share: float) -> DataFrame:
    """A parameterised query over the installed views."""
    return spark.sql("SELECT source, count(*) AS docs, CAST(count(*) * :share AS BIGINT) AS wanted FROM documents GROUP BY source", args={"share": share})


