"""Measures of accuracy and cost."""

from __future__ import annotations

import json
import urllib.request

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Relative standard error times the square root of the number of registers.
MID_RANGE_SCALE = 1.04


def relative_error(estimate: Column, truth: Column) -> Column:
    return estimate / F.when(truth != 0, truth) - 1


def summary(errors: DataFrame, by: list[str], column: str = "rel_err") -> DataFrame:
    """bias, median, stdev and rmse of each group."""
    e = F.col(column)
    return errors.groupBy(*by).agg(F.avg(e).alias("bias"), F.percentile(e, 0.5).alias("median"), F.stddev_pop(e).alias("stdev"), F.sqrt(F.avg(e * e)).alias("rmse"))


def bands(errors: DataFrame, by: list[str], column: str = "rel_err", quantiles: tuple[float, ...] = (0.05, 0.25, 0.75, 0.95)) -> DataFrame:
    """Quantiles of each group."""
    return errors.groupBy(*by).agg(*(F.percentile(F.col(column), q).alias(f"q{round(100 * q):02d}") for q in quantiles))


def operating_range(table: DataFrame, by: list[str], tolerance: float) -> DataFrame:
    """The largest n up to which the absolute bias stays within the tolerance."""
    first_bad = F.min(F.when(F.abs("bias") > tolerance, F.col("n")))
    limit = table.groupBy(*by).agg(first_bad.alias("_bad"))
    return table.join(limit, by).where(F.col("_bad").isNull() | (F.col("n") < F.col("_bad"))).groupBy(*by).agg(F.max("n").alias("up_to"))


def expected_stdev(m: int) -> float:
    return MID_RANGE_SCALE / m**0.5


def register_saving(factor: Column) -> Column:
    """How many times the registers the conventional estimate would need for the same error."""
    return factor * factor


def sketch_bytes(p: int, bits: int) -> int:
    return (1 << p) * bits // 8


def extraction_bound(p: int, bits: int, bandwidth: float) -> float:
    """Seconds to read all registers once."""
    return sketch_bytes(p, bits) / bandwidth


def storage_factor(bits: Column, d: Column, slope: Column) -> Column:
    """Variance of a distance estimate times the bits of a signature's component, where components agree with probability 1 - slope * d."""
    return bits * d * (1 / slope - d)


def shuffle_cost(df: DataFrame) -> dict[str, int]:
    """Records and bytes shuffled by running ``df`` once, from the stage metrics of its own jobs (needs the session's UI)."""
    context = df.sparkSession.sparkContext
    url = context.uiWebUrl
    if not url:
        raise RuntimeError("the session was started without its UI")
    read = lambda: {s["stageId"]: s for s in json.load(urllib.request.urlopen(f"{url}/api/v1/applications/{context.applicationId}/stages"))}  # noqa: E731, S310
    before = set(read())
    df.write.format("noop").mode("overwrite").save()
    own = [s for k, s in read().items() if k not in before]
    return {"records": sum(s["shuffleWriteRecords"] for s in own), "bytes": sum(s["shuffleWriteBytes"] for s in own), "input_records": sum(s["inputRecords"] for s in own)}
