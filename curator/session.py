"""Session settings that the engine expects; a session given by others is used as it is."""

from __future__ import annotations

from pyspark.sql import SparkSession


def local_session(cores: int | str = "*", partitions: int = 8) -> SparkSession:
    """A session for tests and the bench.  On a cluster, submit with the same SQL settings and more partitions."""
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .config("spark.sql.adaptive.enabled", "true")
        .config("spark.sql.shuffle.partitions", str(partitions))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.sql.execution.arrow.pyspark.enabled", "true")
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )


def visible(spark: SparkSession) -> SparkSession:
    """Let the session's Python workers import this package from where the driver has it.

    On a cluster install the package on the workers or pass it with --py-files; the path then changes nothing.
    """
    from pathlib import Path

    root = str(Path(__file__).resolve().parent.parent)
    paths = spark.sparkContext.environment.get("PYTHONPATH", "").split(":")
    if root not in paths:
        spark.sparkContext.environment["PYTHONPATH"] = ":".join([root, *[p for p in paths if p]])
    return spark
