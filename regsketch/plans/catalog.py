"""The queries of this engine by name, and their DuckDB twins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import estimators as E
from ..operators import sketch as S
from ..sources.tables import table
from . import queries_pairs, queries_single, queries_work, registry  # noqa: F401


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct orders by flag and status: exact, and by three estimators from one sketch."""
    keys, spec = queries_single.GRP, queries_single.SPEC
    line = table(spark, sf_dir, "lineitem")
    vectors = S.multiplicity(S.build(line, "l_orderkey", spec, keys), spec, keys)
    found = vectors.select(*keys, *(E.estimate(m, F.col("counts"), spec.p, spec.q).alias(m) for m in ("corrected_raw", "ml", "original")))
    return line.groupBy(*keys).agg(F.countDistinct("l_orderkey").alias("exact")).join(found, keys)


def queries() -> dict:
    return dict(registry.QUERIES)


def oracle_sql() -> dict:
    return dict(registry.ORACLES)
