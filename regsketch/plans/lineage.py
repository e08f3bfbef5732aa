"""Cutting lineage in storage that executors share."""

from __future__ import annotations

import os

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``, else the context's checkpoint folder, else one of our own in the warehouse.

    On a cluster a warehouse on the driver's own disk will not do, as executors would not see it; that is an error.
    """
    if named := spark.conf.get("spark.checkpoint.dir", None):
        return named
    given = spark.sparkContext._jsc.sc().getCheckpointDir()
    if given.isDefined():
        return given.get()
    warehouse = spark.conf.get("spark.sql.warehouse.dir")
    own_disk = "://" not in warehouse and not warehouse.startswith("hdfs:") or warehouse.startswith("file:")
    if own_disk and not spark.sparkContext.master.split("[")[0] == "local":
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    return os.path.join(warehouse, "checkpoints")


def shared_checkpoints(spark: SparkSession) -> None:
    """See that checkpoints go to the shared folder; set it only where none is set."""
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        context.setCheckpointDir(shared_folder(spark))


def cut(df: DataFrame) -> DataFrame:
    """The same rows, read from a checkpoint that outlives executors."""
    shared_checkpoints(df.sparkSession)
    return df.checkpoint(eager=True)
