"""The methods behind one object."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import estimators as E
from .operators import joint as J
from .operators import sketch as S
from .plans import planner
from .plans.spec import SketchSpec


class RegSketch:
    """Distinct counts and set sizes of DataFrames by register sketches."""

    def __init__(self, spark: SparkSession, spec: SketchSpec | None = None):
        self.spark, self.spec = spark, spec or SketchSpec(12, 52)

    def sketch(self, df: DataFrame, item: str, by: list[str] | None = None) -> DataFrame:
        """R1, in the shape that suits the keys by default."""
        return planner.build(df, item, self.spec, by)

    def estimate(self, r1: DataFrame, by: list[str] | None = None, method: str = "ml") -> DataFrame:
        """(by, estimate) of sketches."""
        return S.multiplicity(r1, self.spec, by).select(*(by or []), E.estimate(method, F.col("counts"), self.spec.p, self.spec.q).alias("estimate"))

    def approx_distinct(self, df: DataFrame, item: str, by: list[str] | None = None, method: str = "ml") -> DataFrame:
        """(by, estimate) of a column's distinct values; keys without a value that is not null have 0."""
        found = self.estimate(self.sketch(df, item, by), by, method)
        if not by:
            return found
        found = found.withColumnsRenamed({k: f"_of_{k}" for k in by})
        every = df.select(*by).distinct().join(found, reduce(lambda a, b: a & b, (F.col(k).eqNullSafe(F.col(f"_of_{k}")) for k in by)), "left")
        return every.select(*by, F.coalesce("estimate", F.lit(0.0)).alias("estimate"))

    def rollup(self, r1: DataFrame, keep: list[str]) -> DataFrame:
        return S.rollup(r1, keep)

    def set_ops(self, left: DataFrame, right: DataFrame, item: str, other_item: str | None = None, solver: str = "bfgs") -> DataFrame:
        """One row: only_left, only_right, both, union, jaccard of two columns' sets."""
        sides = left.select(F.lit(1).alias("side"), F.col(item).alias("x")).unionByName(right.select(F.lit(2).alias("side"), F.col(other_item or item).alias("x")))
        return self._solved(S.build(sides, "x", self.spec, ["side"]), solver)

    def set_ops_where(self, df: DataFrame, item: str, left: Column, right: Column, solver: str = "bfgs") -> DataFrame:
        """The same for the rows of one table that meet each of two conditions, from one scan."""
        return self._solved(J.operands(df, item, {1: left, 2: right}, self.spec, S.build), solver)

    def _solved(self, r1: DataFrame, solver: str) -> DataFrame:
        stat = J.pair_statistic(r1.withColumn("_pair", F.lit(1)), self.spec, ["_pair"])
        if solver == "bfgs":
            return J.report(J.solve_bfgs(stat, self.spec)).drop("_pair")
        if solver == "fixed_point":
            rows = J.solve_fixed_point(stat, self.spec).select(F.col("rates.a").alias("only_left"), F.col("rates.b").alias("only_right"), F.col("rates.x").alias("both"), J.identifiable(F.col("stat")).alias("identifiable"))
            return J.report(rows)
        raise ValueError(f"unknown solver {solver!r}; there are bfgs and fixed_point")
