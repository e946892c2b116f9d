"""Intermediate tables in the folder that the whole cluster shares, and what jobs leave behind."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

from ..plans.state import commit as materialize
from ..plans.state import folder, new_folder

__all__ = ["drop", "materialize", "new_folder", "release_shuffles", "small_batches"]


@contextmanager
def small_batches(spark: SparkSession, size: int = 4 << 20) -> Iterator[None]:
    """Within it, jobs hand texts to Python in batches of about ``size`` bytes; the session's own setting comes back after."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(key)
    spark.conf.set(key, str(size))
    try:
        yield
    finally:
        spark.conf.set(key, before)


def drop(df: DataFrame) -> None:
    """Delete the files behind a materialized table that no later plan reads."""
    spark = df.sparkSession
    for name in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if folder(spark).split("://")[-1].lstrip("/") in name:
            hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(name)
            hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(hadoop, True)


def release_shuffles(spark: SparkSession) -> None:
    """Let the context cleaner remove shuffle files of plans that are no longer referenced."""
    spark.sparkContext._jvm.System.gc()
