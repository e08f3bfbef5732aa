"""Choices of plan shape that Catalyst does not make for sketches."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators import sketch as S
from .spec import SketchSpec

#: Keys for each task from which one exchange by key beats dealing by (key, register), if no key is hot.
MANY_KEYS = 10_000
#: Share of the rows from which a key is hot.
HOT = 0.01
#: Rows of partial registers for all tasks together from which dense arrays for each task shuffle less.
DENSE_ROWS = 2_000_000_000


@dataclass(frozen=True)
class Shape:
    """How a build is laid out, and why."""

    name: str
    why: str


def choose_build(keys: int, hot_share: float, tasks: int, spec: SketchSpec) -> Shape:
    """The shape for this many keys, the share of the largest one and the number of scan tasks."""
    if keys > MANY_KEYS * max(1, tasks // 100) and hot_share < HOT:
        return Shape("by_key", "many keys and none is hot: one exchange serves all groupings by key")
    if keys <= 1_000 and tasks * keys * spec.m > DENSE_ROWS:
        return Shape("partitioned", "few keys and very many tasks: a packed array for each task is smaller than its register rows")
    return Shape("by_register", "dealt by key and register, so that a hot key is spread over its registers")


def measure(df: DataFrame, keys: list[str], sample: float = 0.01) -> tuple[int, float]:
    """Approximate number of keys, and the share of the largest in a sample: two numbers for the driver."""
    if not keys:
        return 1, 1.0
    n = df.agg(F.approx_count_distinct(F.struct(*keys)).alias("n")).first()["n"]
    part = df.sample(sample, seed=1).groupBy(*keys).count()
    row = part.agg(F.max("count").alias("top"), F.sum("count").alias("all")).first()
    return n, (row["top"] or 0) / (row["all"] or 1)


def build(df: DataFrame, item: str, spec: SketchSpec, keys: list[str] | None = None, shape: Shape | None = None) -> DataFrame:
    """R1 in the given or the default shape."""
    name = shape.name if shape else "by_register"
    if name == "by_key" and keys:
        return S.build_by_key(df, item, spec, keys)
    if name == "partitioned":
        return S.build_partitioned(df, item, spec, keys)
    return S.build(df, item, spec, keys)


def finest(specs: list[SketchSpec]) -> SketchSpec:
    """One spec that all given ones can be reduced to, so that a single scan serves them."""
    p = max(s.p for s in specs)
    bits = max(s.p + s.q for s in specs)
    if len({(s.algo, s.seed) for s in specs}) != 1:
        raise ValueError("one scan serves specs of one hash function only")
    return SketchSpec(p, bits - p, specs[0].algo, specs[0].seed)


def build_all(df: DataFrame, item: str, specs: list[SketchSpec], keys: list[str] | None = None) -> dict[SketchSpec, DataFrame]:
    """R1 for each spec from one scan."""
    base = finest(specs)
    fine = S.build(df, item, base, keys)
    return {s: S.reduce(fine, base, s.p, s.q, keys) for s in specs}


def predicate_sketches(df: DataFrame, item: str, spec: SketchSpec, conditions: dict[str, Column], keys: list[str] | None = None) -> DataFrame:
    """R1 with column part: the rows that meet each named condition, from one scan."""
    named = F.filter(F.array(*(F.when(c, F.lit(n)) for n, c in conditions.items())), lambda x: x.isNotNull())
    return S.build(df.withColumn("part", F.explode(named)), item, spec, [*(keys or []), "part"])
