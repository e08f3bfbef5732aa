"""Cutting lineage, and names that a table does not have."""

from __future__ import annotations

import gc

from pyspark.sql import SparkSession

from ..plans.lineage import cut, shared_folder

__all__ = ["collect_garbage", "cut", "free", "remove", "shared_folder"]


def collect_garbage(spark: SparkSession) -> None:
    """Have the driver drop what it no longer refers to, as Spark removes shuffle files of finished steps only then."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def free(name: str, taken: list[str]) -> str:
    """A column name like this one that the table does not have, in either case."""
    low = {c.lower() for c in taken}
    while name.lower() in low:
        name = f"_{name}"
    return name


def remove(spark: SparkSession, path: str) -> None:
    """Delete a folder of ours from whichever store it is in."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
