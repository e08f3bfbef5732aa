"""What the estimators are compared with."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import estimators as E
from ..functions.hashing import address, hash_word, present, rank
from ..plans.ship import ship
from ..plans.spec import SketchSpec


def unit(word: Column) -> Column:
    """A hash word as a number from 0 to 1."""
    return F.shiftrightunsigned(word, 1).cast("double") / F.lit(9223372036854775808.0)


def kmv(df: DataFrame, item: str, spec: SketchSpec, k: int, keys: list[str]) -> DataFrame:
    """(keys, least): the k-th smallest hash of each key. Spark cuts each task's rows to its k smallest before the shuffle (a ranked group limit)."""
    u = df.where(F.col(item).isNotNull()).select(*keys, unit(hash_word(F.col(item), spec)).alias("u")).distinct()
    ranked = u.withColumn("r", F.row_number().over(Window.partitionBy(*keys).orderBy("u"))).where(F.col("r") <= k)
    return ranked.groupBy(*keys).agg(F.max("u").alias("least"))


def kmv_size(least: Column, k: int) -> Column:
    return F.lit(float(k - 1)) / least


def kmv_intersection(sides: DataFrame, item: str, spec: SketchSpec, k: int) -> DataFrame:
    """One row with both: how many elements sides 1 and 2 share."""
    u = sides.select("side", unit(hash_word(F.col(item), spec)).alias("u")).groupBy("u").agg((F.bool_or(F.col("side") == 1) & F.bool_or(F.col("side") == 2)).alias("shared"))
    top = u.orderBy("u").limit(k)
    return top.agg((F.sum(F.col("shared").cast("double")) / k * (k - 1) / F.max("u")).alias("both"))


def minwise(sides: DataFrame, item: str, t: int) -> DataFrame:
    """(side, j, h): the least of each of t hash functions."""
    each = sides.select("side", item).distinct().withColumn("j", F.explode(F.sequence(F.lit(1), F.lit(t))))
    word = F.substring(F.md5(F.concat(F.col("j").cast("string"), F.lit(":"), F.col(item).cast("string"))), 1, 16)
    return each.select("side", "j", word.alias("h")).groupBy("side", "j").agg(F.min("h").alias("h"))  # equal lengths: text order is number order


def minwise_equal(sides: DataFrame, item: str, t: int, bits: int | None = None) -> DataFrame:
    """One row with the share of equal least hashes, of their last bits only if asked."""
    own = minwise(sides, item, t)
    if bits:
        own = own.withColumn("h", F.conv(F.substring("h", 16, 1), 16, 10).cast("int").bitwiseAND(F.lit((1 << bits) - 1)))
    wide = own.groupBy("j").agg(F.max(F.when(F.col("side") == 1, F.col("h"))).alias("a"), F.max(F.when(F.col("side") == 2, F.col("h"))).alias("b"))
    return wide.agg(F.avg((F.col("a") == F.col("b")).cast("double")).alias("jaccard"))


def one_permutation(df: DataFrame, item: str, spec: SketchSpec, keys: list[str]) -> DataFrame:
    """(keys, bin, least): the least of the bits after the address in each bin."""
    rows = df.where(F.col(item).isNotNull()).select(*keys, hash_word(F.col(item), spec).alias("h"))
    rest = F.col("h").bitwiseAND(F.lit((1 << (64 - spec.p)) - 1))
    return rows.groupBy(*keys, address(F.col("h"), spec).alias("bin")).agg(F.min(rest).alias("least"))


def simhash(df: DataFrame, key: str, item: str, spec: SketchSpec) -> DataFrame:
    """(key, simhash): 64 bits as text, each set if it is set in over half the items' hashes."""
    h = df.select(key, hash_word(F.col(item), spec).alias("h"))
    sums = [F.sum(F.shiftrightunsigned("h", b).bitwiseAND(F.lit(1)) * 2 - 1).alias(f"_b{b}") for b in range(64)]
    own = h.groupBy(key).agg(*sums)
    return own.select(key, F.concat(*(F.when(F.col(f"_b{b}") > 0, "1").otherwise("0") for b in range(63, -1, -1))).alias("simhash"))


#: Steps of the bias table over the raw estimate.
BIAS_STEPS = 256


def bias_corrected(counts: Column, p: int, q: int) -> Column:
    """Raw estimate less an interpolated bias up to 5 m; linear counting while it is below 0.7 m. The bias comes from an even grid, so its place is found by division."""
    from .simulate import bias_curve

    m = 1 << p
    raw = E.raw(counts, p, q)
    raws, biases = np.array(bias_curve(p, q)).T
    first, step = float(raws[0]), float(raws[-1] - raws[0]) / BIAS_STEPS
    grid = F.lit([float(x) for x in np.interp(first + step * np.arange(BIAS_STEPS + 1), raws, biases)])
    place = F.greatest(F.lit(0.0), F.least(F.lit(BIAS_STEPS - 1e-9), (raw - first) / step))
    at = F.floor(place).cast("int")
    bias = F.get(grid, at) + (place - at) * (F.get(grid, at + 1) - F.get(grid, at))
    fixed = F.when(raw <= 5.0 * m, raw - bias).otherwise(raw)
    low = E.linear(counts, p)
    return F.when(low < 0.7 * m, low).otherwise(fixed)


def hip(df: DataFrame, item: str, order: str, keys: list[str], spec: SketchSpec) -> DataFrame:
    """(keys, estimate): each change of a register adds one over the probability that it could have changed.

    Updates must be taken in order, so a key is one task's work; what cannot change a register again is left before: only the first
    of equal updates goes into the group, at most (q + 1) 2**p rows for each key.
    """
    ship(df.sparkSession)
    word = hash_word(F.col(item), spec)
    rows = df.where(present([F.col(item)])).select(*keys, F.col(order).alias("at"), address(word, spec).alias("idx"), rank(word, spec).alias("rank"))
    firsts = rows.groupBy(*keys, "idx", "rank").agg(F.min("at").alias("at"))
    m, q = spec.m, spec.q

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        registers, chance, total = np.zeros(m, dtype=int), 1.0, 0.0
        weight = lambda k: 0.0 if k > q else 2.0**-k / m
        for idx, value in frame.sort_values(["at", "idx", "rank"])[["idx", "rank"]].itertuples(index=False):
            if value > registers[idx]:
                total += 1 / chance
                chance -= weight(registers[idx]) - weight(value)
                registers[idx] = value
        out = frame[keys].head(1).copy()
        out["estimate"] = total
        return out

    schema = ", ".join([*(f"`{k}` {df.schema[k].dataType.simpleString()}" for k in keys), "estimate double"])
    return firsts.groupBy(*keys).applyInPandas(run, schema)


def self_learning_bitmap(df: DataFrame, item: str, order: str, keys: list[str], bits: int = 4096, most: int = 1_000_000) -> DataFrame:
    """(keys, estimate) by a bitmap with a sampling rate that falls as it fills, so that the relative error is alike up to ``most``.

    It needs elements in order and cannot be merged, so a key is one task's work; but as the rate only falls, an element can set its bit only if
    it has a lower number than all before it at that bit. Only those go into the group: some bits * ln(elements / bits) rows for each key. The loop over them is Python's.
    """
    ship(df.sparkSession)
    word = F.xxhash64(item)
    firsts = df.where(F.col(item).isNotNull()).select(*keys, F.col(order).alias("at"), F.pmod(word, F.lit(bits)).cast("int").alias("bit"), (F.shiftrightunsigned(word, 20).bitwiseAND(F.lit((1 << 30) - 1)) / float(1 << 30)).alias("u")).groupBy(*keys, "bit", "u").agg(F.min("at").alias("at"))
    earlier = Window.partitionBy(*keys, "bit").orderBy("at", "u").rowsBetween(Window.unboundedPreceding, -1)
    firsts = firsts.withColumn("least", F.min("u").over(earlier)).where("least IS NULL OR u < least").drop("least")
    # The error e solves bits = ln(1 + 2 most e**2) / ln(1 + 2 e**2 / (1 - e**2)); rates follow from it.
    low, high = 1e-4, 0.5
    for _ in range(80):
        e = (low + high) / 2
        low, high = (e, high) if np.log(1 + 2 * most * e * e) / np.log(1 + 2 * e * e / (1 - e * e)) > bits else (low, e)
    c = 1 / (low * low)
    r = 1 - 2 / (c + 1)
    limit = int(bits - c / 2)
    full = np.arange(1, bits + 1)
    with np.errstate(over="ignore"):
        rates = (bits / (bits + 1 - np.minimum(full, limit))) * (1 + 1 / c) * r ** np.minimum(full, limit)
        steps = bits / ((bits + 1 - full) * rates)

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        seen, filled, total = np.zeros(bits, dtype=bool), 0, 0.0
        for bit, u in frame.sort_values(["at", "bit", "u"])[["bit", "u"]].itertuples(index=False):
            if filled < limit and not seen[bit] and u < rates[filled]:
                seen[bit] = True
                total += steps[filled]
                filled += 1
        out = frame[keys].head(1).copy()
        out["estimate"] = total
        return out

    schema = ", ".join([*(f"`{k}` {df.schema[k].dataType.simpleString()}" for k in keys), "estimate double"])
    return firsts.groupBy(*keys).applyInPandas(run, schema)
