"""Sketches of known cardinality without inserting elements, and error tables from them."""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.numeric import corrected_raw_many, joint_ml_many, ml_many
from ..plans.ship import ship
from ..plans.spec import SketchSpec


def registers_of(n: int, p: int, q: int, random: np.random.Generator) -> np.ndarray:
    """Register values after n different elements: how often each register is hit, then the largest of so many ranks."""
    m = 1 << p
    hits = np.bincount(random.integers(0, m, n), minlength=m) if n <= 4 * m else random.multinomial(n, np.full(m, 1 / m))
    out = np.zeros(m, dtype=np.int64)
    full = np.flatnonzero(hits)
    out[full] = _largest(hits[full], q, random)
    return out


def _largest(hits: np.ndarray, q: int, random: np.random.Generator) -> np.ndarray:
    """The largest of so many ranks, for each number of hits above 0."""
    with np.errstate(divide="ignore"):
        largest = np.ceil(-np.log2(-np.expm1(np.log(random.random(len(hits))) / hits)))
    return np.clip(largest, 1, q + 1).astype(np.int64)


def counts_of(n: int, p: int, q: int, random: np.random.Generator) -> tuple[int, np.ndarray]:
    """The value counts of a sketch of about n different elements, and how many they are.

    Every register is hit by a Poisson number of elements; given their total, registers are hit as by that many elements one
    after another, so the sketch is exactly one of the total's size. Where fewer different numbers of hits occur than
    registers, the registers of each number are drawn together.
    """
    m = 1 << p
    rate = n / m
    reach = 12 * rate**0.5 + 12
    low, high = max(0, int(rate - reach)), int(rate + reach)
    if high - low + 1 >= m:
        hits = random.poisson(rate, m)
        full = hits[hits > 0]
        return int(hits.sum()), np.bincount(np.concatenate([np.zeros(m - len(full), dtype=np.int64), _largest(full, q, random)]), minlength=q + 2)
    number = np.arange(low, high + 1)
    log = number * np.log(rate) - rate - _log_factorials(low, high)
    share = np.exp(log - log.max())
    registers = random.multinomial(m, share / share.sum())
    used = registers > 0
    number, registers = number[used], registers[used]
    # chance of a largest rank up to k after h hits: (1 - 2**-k)**h
    up_to = np.exp(number[:, None] * np.log1p(-(2.0 ** -np.arange(1, q + 1))))
    steps = np.diff(np.concatenate([np.zeros((len(number), 1)), up_to, np.ones((len(number), 1))], axis=1), axis=1)
    steps[number == 0] = 0
    counts = np.zeros(q + 2, dtype=np.int64)
    hit = number > 0
    counts[0] = registers[~hit].sum()
    steps = np.maximum(steps[hit], 0)
    counts[1:] = random.multinomial(registers[hit], steps / steps.sum(1, keepdims=True)).sum(0)
    return int((number * registers).sum()), counts


@lru_cache(maxsize=64)
def _log_factorials(low: int, high: int) -> np.ndarray:
    from math import lgamma

    return lgamma(low + 1) + np.concatenate([[0.0], np.cumsum(np.log(np.arange(low + 1, high + 1)))])


def draw_registers(spark: SparkSession, n: int, spec: SketchSpec, runs: int, seed: int = 1) -> DataFrame:
    """(run, counts): value counts of ``runs`` independent sketches of n elements."""
    ship(spark)
    p, q = spec.p, spec.q

    def draw(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            rows = [(int(r), np.bincount(registers_of(n, p, q, np.random.default_rng([seed, n, int(r)])), minlength=q + 2).tolist()) for r in frame["id"]]
            yield pd.DataFrame(rows, columns=["run", "counts"])

    return spark.range(runs).mapInPandas(draw, "run bigint, counts array<bigint>")


def shuffle_registers(counts: DataFrame, p: int, seed: int = 1, parts: int = 64) -> DataFrame:
    """R1 with the value counts of one row of R3, values dealt to registers at random: every register gets the next place of a seeded permutation of 0 .. 2**p - 1.

    The permutation is a keyed mixing of the place's bits, which is one to one, so that no row has to know another; the values' places are running sums of the counts.
    """
    value = F.posexplode("counts").alias("reg", "c")
    each = counts.select(value, F.col("counts")).where("c > 0").withColumn("first", F.aggregate(F.slice("counts", F.lit(1), F.col("reg")), F.lit(0).cast("bigint"), lambda a, c: a + c))
    blocks = each.where("reg > 0").withColumn("block", F.explode(F.sequence(F.lit(0), F.floor((F.col("c") - 1) / (1 << 12))))).repartition(parts, "reg", "block")
    begin = F.col("block") * (1 << 12)
    own = blocks.select("reg", F.explode(F.sequence(F.col("first") + begin, F.col("first") + F.least(F.col("c"), begin + (1 << 12)) - 1)).alias("place"))
    return own.select(_mixed_place(F.col("place"), p, seed).cast("int").alias("idx"), F.col("reg").cast("tinyint").alias("reg"))


def _mixed_place(place: Column, p: int, seed: int) -> Column:
    """A permutation of the numbers of p bits: rounds of multiplication by odd numbers and of xor with the upper half, all modulo 2**p."""
    mask, half = (1 << p) - 1, max(1, (p + 1) // 2)
    random = np.random.default_rng([seed, p])
    for _ in range(4):
        factor, shift = int(random.integers(1, 1 << 30)) | 1, int(random.integers(0, 1 << 30))
        place = (place * F.lit(factor) + F.lit(shift)).bitwiseAND(F.lit(mask).cast("bigint"))
        place = place.bitwiseXOR(F.shiftrightunsigned(place, half))
    return place


def pair_of(a: int, b: int, x: int, p: int, q: int, random: np.random.Generator) -> dict[str, np.ndarray]:
    """The statistic of two sketches with so many elements apart and in common."""
    own_a, own_b, shared = (registers_of(n, p, q, random) for n in (a, b, x))
    s1, s2 = np.maximum(own_a, shared), np.maximum(own_b, shared)
    count = lambda values, mask: np.bincount(values[mask], minlength=q + 2).astype(float)
    return {"lt1": count(s1, s1 < s2), "gt1": count(s1, s1 > s2), "lt2": count(s2, s2 < s1), "gt2": count(s2, s2 > s1), "eq": count(s1, s1 == s2)}


#: Sizes of A, B and X: Jaccard 0 to 0.83, ratios 1 to 100, small and large against the number of registers.
JOINT_GRID = ((1_000, 1_000, 1_000), (100_000, 100_000, 100_000), (1_000_000, 1_000_000, 100_000), (100_000, 100_000, 1_000), (1_000_000, 10_000, 10_000), (100, 100_000, 100_000), (100_000, 100_000, 1_000_000), (100_000, 100_000, 0))


def joint_samples(spark: SparkSession, spec: SketchSpec, runs: int, grid=JOINT_GRID, seed: int = 1) -> DataFrame:
    """(config, run, target, truth, conventional, joint, iterations) of simulated pairs."""
    ship(spark)
    p, q = spec.p, spec.q

    def sample(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            if not len(frame):
                continue
            at, run = np.divmod(frame["id"].to_numpy(), runs)
            pairs = [pair_of(*grid[c], p, q, np.random.default_rng([seed, int(c), int(r)])) for c, r in zip(at, run, strict=True)]
            stats = np.array([[s[k] for k in ("lt1", "gt1", "lt2", "gt2", "eq")] for s in pairs])
            found, rounds, _ = joint_ml_many(stats, p, q)
            lt1, gt1, lt2, gt2, eq = (stats[:, k].astype(np.int64) for k in range(5))
            n1, n2, nu = (ml_many(v)[0] for v in (lt1 + gt1 + eq, lt2 + gt2 + eq, gt1 + gt2 + eq))
            a, b, x = (np.array([grid[c][k] for c in at], dtype=float) for k in range(3))
            names = [",".join(map(str, grid[c])) for c in at]
            values = {"only_left": (a, nu - n2, found[:, 0]), "only_right": (b, nu - n1, found[:, 1]), "both": (x, n1 + n2 - nu, found[:, 2]), "union": (a + b + x, nu, found.sum(1))}
            for t, (truth, conventional, joint) in values.items():
                yield pd.DataFrame({"config": names, "run": run, "target": t, "truth": truth, "conventional": conventional, "joint": joint, "iterations": rounds})

    return spark.range(len(grid) * runs).repartition(4 * spark.sparkContext.defaultParallelism).mapInPandas(sample, "config string, run bigint, target string, truth double, conventional double, joint double, iterations bigint")


def joint_error_grid(samples: DataFrame) -> DataFrame:
    """(config, target, runs, mean truth, mean, standard deviation and root mean square error of both estimates, factor, iterations): how much better the joint estimate is."""
    rmse = lambda c: F.sqrt(F.avg((F.col(c) - F.col("truth")) ** 2)).alias(f"rmse_{c}")
    each = [f(c) for c in ("conventional", "joint") for f in (lambda c: F.avg(c).alias(f"mean_{c}"), lambda c: F.stddev_pop(F.col(c) - F.col("truth")).alias(f"stdev_{c}"), rmse)]
    out = samples.groupBy("config", "target").agg(F.count(F.lit(1)).alias("runs"), F.avg("truth").alias("truth"), *each, F.avg("iterations").alias("iterations"))
    return out.withColumn("factor", F.try_divide("rmse_conventional", "rmse_joint"))


@lru_cache
def truncation_factor(keep: float = 0.7, p: int = 12, q: int = 20, n: int = 200_000, runs: int = 40) -> float:
    """The factor that makes the truncated geometric mean unbiased, by simulation with fixed seeds."""
    m = 1 << p
    means = []
    for run in range(runs):
        values = np.sort(registers_of(n, p, q, np.random.default_rng([97, run])))[: int(keep * m)]
        means.append(m * 2.0 ** values.mean())
    return float(n / np.mean(means))


@lru_cache
def bias_curve(p: int = 12, q: int = 20, points: int = 120, runs: int = 20_000) -> tuple[tuple[float, float], ...]:
    """(raw estimate, bias) at cardinalities from 0 to 6 m, by simulation with fixed seeds: the table of an empirical correction.

    Value counts are drawn for a Poisson number of elements, whose registers are independent: one multinomial draw for each run.
    """
    m = 1 << p
    weights = 2.0 ** -np.arange(q + 2)
    out = []
    for k in range(points + 1):
        n = max(1, 6 * m * k // points)
        up_to = np.exp(-n / m * 2.0 ** -np.arange(q + 1))
        share = np.diff(np.concatenate([[0.0], up_to, [1.0]]))
        raws = 0.7213475204444817 * m * m / (np.random.default_rng([98, k]).multinomial(m, share / share.sum(), runs) @ weights)
        out.append((float(raws.mean()), float(raws.mean() - n)))
    return tuple(sorted(out))


#: Two sizes for each factor of ten, up to 5e10.
SIZES = tuple(int(10 ** (k / 2)) for k in range(2, 22)) + (50_000_000_000,)


def error_samples(spark: SparkSession, spec: SketchSpec, cardinalities: list[int], runs: int, seed: int = 1, batch: int = 250) -> DataFrame:
    """(n, run, method, rel_err) of the corrected raw and the likelihood estimate over simulated sketches, large cardinalities too."""
    ship(spark)
    p, q = spec.p, spec.q
    blocks = -(-runs // batch)

    def sample(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for k in frame["id"]:
                at, block = divmod(int(k), blocks)
                n, first = cardinalities[at], block * batch
                random = np.random.default_rng([seed, p, q, at, block])
                drawn = [counts_of(n, p, q, random) for _ in range(min(batch, runs - first))]
                sizes, counts = np.array([s for s, _ in drawn], dtype=float), np.array([c for _, c in drawn])
                some = sizes > 0
                for method, found in (("corrected_raw", corrected_raw_many(counts)), ("ml", ml_many(counts)[0])):
                    yield pd.DataFrame({"n": n, "run": first + np.flatnonzero(some), "method": method, "rel_err": found[some] / sizes[some] - 1})

    return spark.range(len(cardinalities) * blocks).repartition(2 * spark.sparkContext.defaultParallelism, F.xxhash64("id")).mapInPandas(sample, "n bigint, run bigint, method string, rel_err double")
