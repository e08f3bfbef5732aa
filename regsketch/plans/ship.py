"""Getting this package to Python workers."""

from __future__ import annotations

import os
import tempfile
import zipfile

from pyspark.sql import DataFrame, SparkSession

import regsketch

_shipped: dict[str, str] = {}

#: Bytes of rows in a batch that goes to a Python worker, where many steps share an executor's memory. By itself Spark gathers up to 64 MB, or 10,000 texts, and holds them
#: some four times: in the JVM's vectors and its send buffer, each grown by doubling, and in the worker beside the batch before.
BATCH_BYTES = 4 << 20


def ship(spark: SparkSession) -> None:
    """Send the package's source to the executors, once for each application."""
    context = spark.sparkContext
    if context.applicationId in _shipped:
        return
    top = os.path.dirname(os.path.abspath(regsketch.__file__))
    if os.path.isdir(top):  # else it came in an archive of its own
        path = os.path.join(tempfile.mkdtemp(prefix="regsketch-"), "regsketch.zip")
        with zipfile.ZipFile(path, "w") as archive:
            for folder, _, names in os.walk(top):
                for name in sorted(names):
                    if name.endswith(".py"):
                        full = os.path.join(folder, name)
                        archive.write(full, os.path.relpath(full, os.path.dirname(top)))
        context.addPyFile(path)
    _shipped[context.applicationId] = top


def small_batches(spark: SparkSession) -> None:
    """From now on the session hands rows to Python workers in batches of ``BATCH_BYTES``, or one longer row by itself; a size that was set for it stays."""
    if (name := "spark.sql.execution.arrow.maxBytesPerBatch") not in spark.conf.getAll:
        spark.conf.set(name, str(BATCH_BYTES))


def released() -> None:
    """Give memory that Arrow and the C library keep for later back to the system: a worker serves many tasks beside the JVM."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except OSError:  # another C library
        pass


def map_arrow(df: DataFrame, function, schema: str) -> DataFrame:
    """``df.mapInArrow`` with this package at hand in the workers, which give memory back after each task."""
    ship(df.sparkSession)

    def run(batches):
        try:
            yield from function(batches)
        finally:
            released()

    return df.mapInArrow(run, schema)
