"""A store of sketches: R1 as Parquet with its spec, updated by the register-wise maximum.

Taking a maximum twice changes nothing, so deliveries that are repeated after a failure leave the right registers.
Each update writes a new version beside the old one and then names it in a small table; readers see whole versions.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.utils import AnalysisException

from ..operators.sketch import merge
from ..plans.spec import SketchSpec

CATALOGUE = "version bigint, batch bigint, p int, q int, hash string, seed int"


class SketchStore:
    """Sketches with the same keys and spec in one folder."""

    def __init__(self, spark: SparkSession, path: str, keys: list[str], spec: SketchSpec):
        self.spark, self.path, self.keys, self.spec = spark, path, keys, spec

    def _catalogue(self) -> DataFrame | None:
        try:
            return self.spark.read.schema(CATALOGUE).parquet(f"{self.path}/catalogue")
        except AnalysisException:
            return None

    def latest(self) -> tuple[int, int] | None:
        """Version and the batch it came from; the spec there must be this one."""
        table = self._catalogue()
        row = table.orderBy(F.desc("version")).first() if table is not None else None
        if row is None:
            return None
        if (row["p"], row["q"], row["hash"], row["seed"]) != (self.spec.p, self.spec.q, self.spec.algo, self.spec.seed):
            raise ValueError(f"the store holds ({row['p']},{row['q']}) sketches of {row['hash']}, seed {row['seed']}")
        return row["version"], row["batch"]

    def read(self, version: int | None = None) -> DataFrame | None:
        """R1 of a version, the latest by default; None if there is none."""
        if version is None:
            found = self.latest()
            if found is None:
                return None
            version = found[0]
        return self.spark.read.parquet(f"{self.path}/v{version}")

    def update(self, delta: DataFrame, batch: int = -1) -> int:
        """Merge R1 rows into the store; returns the new version. A batch that is already in is left."""
        found = self.latest()
        if found and batch >= 0 and found[1] >= batch:
            return found[0]
        old = self.read(found[0]) if found else None
        full = merge(delta, old, keys=self.keys) if old is not None else merge(delta, keys=self.keys)
        version = found[0] + 1 if found else 0
        full.sortWithinPartitions(*self.keys, "idx").write.mode("overwrite").parquet(f"{self.path}/v{version}")
        s = self.spec
        self.spark.createDataFrame([(version, batch, s.p, s.q, s.algo, s.seed)], CATALOGUE).coalesce(1).write.mode("append").parquet(f"{self.path}/catalogue")
        return version


def write_packed(r2: DataFrame, path: str, partition_by: list[str] | None = None) -> None:
    """R2 for point reads, partitioned by day or key if asked."""
    writer = r2.write.mode("overwrite")
    (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)


def read_elements(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """Elements from Parquet, ORC, JSON lines or CSV."""
    reader = spark.read.options(**options)
    reader = reader.schema(schema) if schema else reader
    return reader.format(kind).load(path)
