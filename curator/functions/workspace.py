"""Durable intermediate tables.

Long jobs cut their lineage by writing a Parquet table into the folder that the cluster shares
(``spark.checkpoint.dir``) and reading it back.  A lost executor then costs a re-read, never a
re-run of everything before, and no block lives in one executor's memory only.
"""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_own_root: str | None = None


def shared_root(spark: SparkSession) -> str:
    """The shared folder named by the session; a private one only where none is set and all tasks run in this process."""
    global _own_root
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if named:
        return named.rstrip("/")
    if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    if _own_root is None:
        _own_root = tempfile.mkdtemp(prefix="curator-")
        atexit.register(shutil.rmtree, _own_root, ignore_errors=True)
    return _own_root


def stash(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` as Parquet into the shared folder and return it as read back."""
    spark = df.sparkSession
    path = f"{shared_root(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._stash_path = path
    return out


def release(df: DataFrame | None) -> None:
    """Delete a table made by :func:`stash` once nothing reads it any more."""
    path = getattr(df, "_stash_path", None)
    if path is None:
        return
    jvm = df.sparkSession._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(where, True)
