"""Two sketches: pair statistics, inclusion-exclusion and joint maximum likelihood.

R5 is (pair keys, stat), five arrays of q + 2 counts: values of the first sketch where it is smaller
(lt1) or larger (gt1), of the second where it is smaller (lt2) or larger (gt2), and of equal registers (eq).
Everything after the statistic works on these arrays, one row for each pair.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce as fold

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import estimators as E
from ..functions.numeric import joint_ml_many, joint_rounds_many
from ..plans.ship import map_arrow
from ..plans.spec import SketchSpec

CASES = ("lt1", "gt1", "lt2", "gt2", "eq")


def pair_tall(r1: DataFrame, spec: SketchSpec, pairs: list[str], side: str = "side") -> DataFrame:
    """(pairs, kind, k, c): the statistic of sides 1 and 2 of one R1 table, from one aggregation by (pair, idx); nothing is joined."""
    reg = lambda s: F.coalesce(F.max(F.when(F.col(side) == s, F.col("reg"))), F.lit(0)).cast("int")
    both = r1.groupBy(*pairs, "idx").agg(reg(1).alias("k1"), reg(2).alias("k2"))
    entry = lambda kind, k: F.struct(F.lit(kind).alias("kind"), F.col(k).alias("k"))
    rows = F.when(F.col("k1") < F.col("k2"), F.array(entry("lt1", "k1"), entry("gt2", "k2"))).when(F.col("k1") > F.col("k2"), F.array(entry("gt1", "k1"), entry("lt2", "k2"))).otherwise(F.array(entry("eq", "k1")))
    counted = both.select(*pairs, F.explode(rows).alias("x")).groupBy(*pairs, F.col("x.kind").alias("kind"), F.col("x.k").alias("k")).agg(F.count(F.lit(1)).alias("c"))
    half = F.when(F.col("kind").isin("lt1", "gt1", "eq"), F.col("c"))
    empty = counted.groupBy(*pairs).agg((F.lit(spec.m) - F.coalesce(F.sum(half), F.lit(0))).alias("c")).where("c > 0")
    return counted.unionByName(empty.select(*pairs, F.lit("eq").alias("kind"), F.lit(0).alias("k"), "c"))


def pair_statistic(r1: DataFrame, spec: SketchSpec, pairs: list[str], side: str = "side") -> DataFrame:
    """R5."""
    tall = pair_tall(r1, spec, pairs, side)
    cell = lambda kind, k: F.coalesce(F.sum(F.when((F.col("kind") == kind) & (F.col("k") == k), F.col("c"))), F.lit(0).cast("bigint"))
    arrays = [F.array(*(cell(kind, k) for k in range(spec.q + 2))).alias(kind) for kind in CASES]
    return tall.groupBy(*pairs).agg(F.struct(*arrays).alias("stat"))


def _added(*arrays: Column) -> Column:
    return fold(lambda a, b: F.zip_with(a, b, lambda x, y: x + y), arrays)


def marginals(stat: Column) -> dict[str, Column]:
    """Multiplicity vectors of both sketches, of their union and of the register-wise minimum."""
    s = {k: stat[k] for k in CASES}
    return {"s1": _added(s["lt1"], s["gt1"], s["eq"]), "s2": _added(s["lt2"], s["gt2"], s["eq"]), "union": _added(s["gt1"], s["gt2"], s["eq"]), "least": _added(s["lt1"], s["lt2"], s["eq"])}


def invariants(stat: Column, spec: SketchSpec) -> dict[str, Column]:
    """What must hold of every statistic."""
    total = lambda a: F.aggregate(a, F.lit(0).cast("bigint"), lambda x, y: x + y)
    first, last = lambda a: F.get(a, F.lit(0)), lambda a: F.get(a, F.lit(spec.q + 1))
    return {
        "zero_cells": (last(stat["lt1"]) == 0) & (first(stat["gt1"]) == 0) & (last(stat["lt2"]) == 0) & (first(stat["gt2"]) == 0),
        "sums_equal": (total(stat["lt1"]) == total(stat["gt2"])) & (total(stat["gt1"]) == total(stat["lt2"])),
        "total_is_m": total(stat["lt1"]) + total(stat["gt1"]) + total(stat["eq"]) == spec.m,
    }


def single_estimates(stat: Column, spec: SketchSpec, epsilon: float = 1e-2) -> dict[str, Column]:
    """Likelihood estimates of both sets and of their union."""
    own = marginals(stat)
    return {k: E.ml(own[k], spec.p, spec.q, epsilon) for k in ("s1", "s2", "union")}


def inclusion_exclusion(one: Column, two: Column, union: Column, clipped: bool = False) -> dict[str, Column]:
    """Sizes by inclusion-exclusion; they may be negative unless clipped."""
    out = {"only_left": union - two, "only_right": union - one, "both": one + two - union}
    return {k: F.greatest(v, F.lit(0.0)) for k, v in out.items()} if clipped else out


def disjoint(stat: Column) -> Column:
    """Whether every register is empty on one side: then nothing is shared."""
    return F.aggregate(F.slice(_added(stat["lt1"], stat["lt2"], stat["eq"]), 2, 1_000), F.lit(0).cast("bigint"), lambda x, y: x + y) == 0


def identifiable(stat: Column) -> Column:
    """False if one sketch's registers are above the other's throughout: how much is shared can then not be told."""
    total = lambda a: F.aggregate(a, F.lit(0).cast("bigint"), lambda x, y: x + y)
    return ~(((total(stat["lt1"]) + total(stat["eq"])) == 0) | ((total(stat["lt2"]) + total(stat["eq"])) == 0))


def pair_pmf(k1: Column, k2: Column, a: Column, b: Column, x: Column, m: int, q: int) -> Column:
    """Probability of a pair of register values, from the joint distribution function."""

    def cdf(u: Column, v: Column) -> Column:
        part = lambda k, rate: F.when(k > q, 0.0).otherwise(rate / (F.lit(float(m)) * F.pow(F.lit(2.0), k.cast("double"))))
        return F.when((u < 0) | (v < 0), 0.0).otherwise(F.exp(-part(u, a) - part(v, b) - part(F.least(u, v), x)))

    return cdf(k1, k2) - cdf(k1 - 1, k2) - cdf(k1, k2 - 1) + cdf(k1 - 1, k2 - 1)


def loglik(stat: Column, a: Column, b: Column, x: Column, p: int, q: int) -> Column:
    """Log-likelihood of the three rates."""
    m = float(1 << p)
    cell = lambda kind, k: F.get(stat[kind], F.lit(k)).cast("double")
    times = lambda c, v: F.when(c > 0, c * F.log(v)).otherwise(0.0)
    total = F.lit(0.0)
    for k in range(1, q + 2):
        w = 2.0 ** -min(k, q) / m
        za, zb, zx = (-F.expm1(-r * w) for r in (a, b, x))
        yx = F.exp(-x * w)
        total = total + times(cell("lt1", k), zx + yx * za) + times(cell("lt2", k), zx + yx * zb) + times(cell("gt1", k), za) + times(cell("gt2", k), zb) + times(cell("eq", k), zx + yx * za * zb)
    for k in range(q + 1):
        w = 2.0**-k / m
        lt1, lt2, gt1, gt2, eq = (cell(kind, k) for kind in ("lt1", "lt2", "gt1", "gt2", "eq"))
        total = total - ((lt1 + eq + gt1) * a + (lt2 + eq + gt2) * b + (lt1 + eq + lt2) * x) * w
    return total


def _gradient_parts(stat: Column, a: Column, b: Column, x: Column, p: int, q: int) -> tuple[Column, Column, Column]:
    """The positive parts of the gradient in the logs of the rates, divided by the rates."""
    m = float(1 << p)
    out = [F.lit(0.0)] * 3
    ratio = lambda c, top, bottom: F.when((c > 0) & (bottom > 0), c * top / F.when(bottom > 0, bottom)).otherwise(0.0)
    for k in range(1, q + 2):
        w = 2.0 ** -min(k, q) / m
        za, zb, zx = (-F.expm1(-r * w) for r in (a, b, x))
        ya, yb, yx = (F.exp(-r * w) for r in (a, b, x))
        lt1, lt2, gt1, gt2, eq = (F.get(stat[kind], F.lit(k)).cast("double") for kind in ("lt1", "lt2", "gt1", "gt2", "eq"))
        d1, d2, de = zx + yx * za, zx + yx * zb, zx + yx * za * zb
        out[0] = out[0] + (ratio(lt1, yx * ya, d1) + ratio(eq, yx * ya * zb, de) + ratio(gt1, ya, za)) * w
        out[1] = out[1] + (ratio(lt2, yx * yb, d2) + ratio(eq, yx * yb * za, de) + ratio(gt2, yb, zb)) * w
        out[2] = out[2] + (ratio(lt1, yx * ya, d1) + ratio(lt2, yx * yb, d2) + ratio(eq, yx * (ya + za * yb), de)) * w
    return tuple(out)


def _linear_parts(stat: Column, p: int, q: int) -> tuple[Column, Column, Column]:
    m = float(1 << p)
    out = [F.lit(0.0)] * 3
    for k in range(q + 1):
        lt1, lt2, gt1, gt2, eq = (F.get(stat[kind], F.lit(k)).cast("double") for kind in ("lt1", "lt2", "gt1", "gt2", "eq"))
        w = 2.0**-k / m
        out = [out[0] + (lt1 + eq + gt1) * w, out[1] + (lt2 + eq + gt2) * w, out[2] + (lt1 + eq + lt2) * w]
    return tuple(out)


def solve_fixed_point(df: DataFrame, spec: SketchSpec, rounds: int = 200) -> DataFrame:
    """R5 with column rates (a, b, x): each rate times positive over linear part of its gradient, again and again, in JVM expressions alone."""
    stat = F.col("stat")
    singles = single_estimates(stat, spec)
    start = inclusion_exclusion(singles["s1"], singles["s2"], singles["union"])
    floor = lambda c: F.greatest(c, F.lit(1.0))
    linear = _linear_parts(stat, spec.p, spec.q)
    df = df.withColumn("_fix", F.struct(floor(start["only_left"]).alias("a"), floor(start["only_right"]).alias("b"), floor(start["both"]).alias("x"), *(c.alias(n) for c, n in zip(linear, ("la", "lb", "lx"), strict=True))))
    fix = F.col("_fix")

    def step(s: Column, _: Column) -> Column:
        parts = _gradient_parts(stat, s["a"], s["b"], s["x"], spec.p, spec.q)
        return F.struct(*((s[n] * parts[k] / F.when(fix[f"l{n}"] > 0, fix[f"l{n}"])).alias(n) for k, n in enumerate("abx")))

    first = F.struct(fix["a"].alias("a"), fix["b"].alias("b"), fix["x"].alias("x"))
    return df.withColumn("rates", F.aggregate(F.sequence(F.lit(1), F.lit(rounds)), first, step)).drop("_fix")


def solve_bfgs(r5: DataFrame, spec: SketchSpec, tolerance: float | None = None) -> DataFrame:
    """R5's keys with only_left, only_right, both, iterations, identifiable: joint maximum likelihood by a quasi-Newton search in log rates, all pairs of an Arrow batch side by side."""
    keys = [c for c in r5.columns if c != "stat"]
    p, q = spec.p, spec.q

    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            sizes, rounds, known = joint_ml_many(_stats(batch, q), p, q, tolerance)
            own = [batch.column(k) for k in keys]
            new = [*(pa.array(np.ascontiguousarray(sizes[:, k])) for k in range(3)), pa.array(rounds.astype(np.int32)), pa.array(known)]
            yield pa.RecordBatch.from_arrays([*own, *new], names=[*keys, "only_left", "only_right", "both", "iterations", "identifiable"])

    schema = ", ".join([*(f"`{k}` {r5.schema[k].dataType.simpleString()}" for k in keys), "only_left double, only_right double, both double, iterations int, identifiable boolean"])
    return map_arrow(r5, solve, schema)


def _stats(batch: pa.RecordBatch, q: int) -> np.ndarray:
    """Column stat as (pairs, 5, q + 2)."""
    stat = batch.column("stat")
    return np.stack([stat.field(k).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, q + 2) for k in CASES], axis=1)


def solve_rounds(r5: DataFrame, spec: SketchSpec, rounds: int) -> DataFrame:
    """R5's keys with only_left, only_right, both after so many rounds of the fixed point, all pairs of an Arrow batch side by side."""
    keys = [c for c in r5.columns if c != "stat"]
    p, q = spec.p, spec.q

    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes = joint_rounds_many(_stats(batch, q), p, q, rounds)
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in keys), *(pa.array(np.ascontiguousarray(sizes[:, k])) for k in range(3))], names=[*keys, "only_left", "only_right", "both"])

    schema = ", ".join([*(f"`{k}` {r5.schema[k].dataType.simpleString()}" for k in keys), "only_left double, only_right double, both double"])
    return map_arrow(r5, solve, schema)


def report(estimates: DataFrame) -> DataFrame:
    """Union and Jaccard similarity added to three disjoint sizes."""
    union = F.col("only_left") + F.col("only_right") + F.col("both")
    return estimates.withColumn("union", union).withColumn("jaccard", F.when(union > 0, F.col("both") / F.when(union > 0, union)))


def operands(df: DataFrame, item: str, sides: dict[int, Column], spec: SketchSpec, build: Callable) -> DataFrame:
    """R1 with column side from one scan: each row goes to the sides whose condition it meets."""
    chosen = F.filter(F.array(*(F.when(cond, F.lit(s)) for s, cond in sides.items())), lambda x: x.isNotNull())
    return build(df.withColumn("side", F.explode(chosen)), item, spec, ["side"])


def pairwise(r1: DataFrame, key: str, spec: SketchSpec) -> DataFrame:
    """R1 with columns left_key, right_key, side for every unordered pair of keys, ready for ``pair_statistic``.

    Each key's registers are repeated for its pairs; the pairs come from the distinct keys, which must be few.
    """
    names = r1.select(key).distinct()
    pairs = names.select(F.col(key).alias("left_key")).join(names.select(F.col(key).alias("right_key")), F.col("left_key") < F.col("right_key"))
    one = pairs.join(r1, F.col("left_key") == F.col(key)).select("left_key", "right_key", F.lit(1).alias("side"), "idx", "reg")
    two = pairs.join(r1, F.col("right_key") == F.col(key)).select("left_key", "right_key", F.lit(2).alias("side"), "idx", "reg")
    return one.unionByName(two)


def incl_excl_k(r1: DataFrame, key: str, values: list, spec: SketchSpec) -> DataFrame:
    """The size of the intersection of up to four sketches: signed sum of the estimates of all 2**k - 1 unions."""
    if not 2 <= len(values) <= 4:
        raise ValueError("two to four sketches: the number of unions doubles with each")
    from .sketch import multiplicity, rollup

    masks = [[mask for mask in range(1, 1 << len(values)) if mask >> i & 1] for i in range(len(values))]
    of = fold(lambda c, i: F.when(F.col(key) == values[i], F.array(*(F.lit(x) for x in masks[i]))).otherwise(c), range(len(values)), F.lit(None).cast("array<int>"))
    unions = rollup(r1.withColumn("mask", F.explode(of)), ["mask"])
    sized = multiplicity(unions, spec, ["mask"]).select(F.when(F.bit_count("mask") % 2 == 1, 1).otherwise(-1).alias("sign"), E.ml(F.col("counts"), spec.p, spec.q, 1e-12).alias("n"))
    return sized.agg(F.sum(F.col("sign") * F.col("n")).alias("estimate"))
