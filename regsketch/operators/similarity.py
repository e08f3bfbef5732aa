"""Registers as a similarity hash."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.model import ALPHA
from ..plans.spec import SketchSpec


def equal_registers(r1: DataFrame, spec: SketchSpec, pairs: list[str], side: str = "side") -> DataFrame:
    """(pairs, equal): the share of registers equal in sides 1 and 2; registers empty in both count as equal."""
    reg = lambda s: F.coalesce(F.max(F.when(F.col(side) == s, F.col("reg"))), F.lit(0))
    both = r1.groupBy(*pairs, "idx").agg(reg(1).alias("k1"), reg(2).alias("k2"))
    return both.groupBy(*pairs).agg((1 - F.sum((F.col("k1") != F.col("k2")).cast("double")) / spec.m).alias("equal"))


def jaccard_from_equal(equal: Column) -> Column:
    """Similarity by the linear approximation: distance = (1 - share) / alpha, within 0 and 1."""
    return 1 - F.least(F.lit(1.0), F.greatest(F.lit(0.0), (1 - equal) / ALPHA))


def equal_probability(d: Column, balance: Column) -> Column:
    """Chance that a register is equal at Jaccard distance d; balance = ab / (a + b)**2 for what is in one set only."""
    return 1 + 2 * ALPHA * F.log(1 - d / 2 + d * d * balance / 4)


def equal_bounds(d: Column) -> tuple[Column, Column]:
    """Bounds over all balances: all on one side, and half on each."""
    return equal_probability(d, F.lit(0.0)), equal_probability(d, F.lit(0.25))


def distance_interval(equal: Column) -> tuple[Column, Column]:
    """Distances for which the share lies within the bounds: the inverses of both."""
    e = F.exp((equal - 1) / (2 * ALPHA))
    low = F.least(F.lit(1.0), F.greatest(F.lit(0.0), 2 * (1 - e)))
    # half on each side: (1 - d / 4)**2 = e
    high = F.least(F.lit(1.0), F.greatest(F.lit(0.0), 4 * (1 - F.sqrt(F.greatest(F.lit(0.0), e)))))
    return low, high


#: Registers of a band, and the least of them above 0.
BAND, FILLED = 8, 4
#: Sketches of fewer registers above 0 than the second have least hashes for bands; those of the first or more have bands of registers. Similar sketches have one way in common.
DENSE_FROM, SPARSE_BELOW = 96, 144
#: Bands of least hashes, hashes of a band, and the modulus of x -> (a x + b) mod PRIME.
LEAST_BANDS, LEAST_ROWS, PRIME = 16, 5, 2_147_483_647
#: The share of equal registers, among those above 0 in either sketch, from which sketches count as similar: a Jaccard similarity of 0.8 for few elements, of 0.72 for many.
CUT = 0.8


def least_factors() -> list[tuple[int, int]]:
    """a and b of each hash, from a fixed generator."""
    state, out = 12345, []
    for _ in range(2 * LEAST_BANDS * LEAST_ROWS):
        state = (1_103_515_245 * state + 12_345) % (1 << 31)
        out.append(1 + state % (PRIME - 1))
    return list(zip(out[::2], out[1::2], strict=True))


def entry_lists(r1: DataFrame, key: str) -> DataFrame:
    """(key, entries): every sketch of at most 256 registers as one sorted list of 64 idx + reg."""
    return r1.groupBy(key).agg(F.sort_array(F.collect_list((F.col("idx") * 64 + F.col("reg")).cast("int"))).alias("entries"))


def bands(entries: DataFrame, key: str, m: int) -> DataFrame:
    """(key, band, bucket): runs of registers of dense sketches, runs of least hashes of sparse ones; equal runs share a bucket.

    With a share of 0.8 a band of eight registers is equal with 0.17 or more, and one of 32 bands with 0.99; five least hashes are
    equal with 0.33, and one of 16 bands with 0.99. Sketches of unlike sets share a band with some 1e-5.
    """
    e = F.col("entries")
    own = F.transform(F.sequence(F.lit(0), F.lit(m // BAND - 1)), lambda b: F.struct(b.alias("band"), F.filter(e, lambda x: F.floor(x / (64 * BAND)) == b).alias("run")))
    runs = F.transform(F.filter(own, lambda r: F.size(r["run"]) >= FILLED), lambda r: F.struct(r["band"].cast("int").alias("band"), F.array_join(r["run"].cast("array<string>"), ",").alias("bucket")))

    def least_hash(a: int, b: int) -> Column:
        return F.array_min(F.transform(e, lambda x: (x.cast("bigint") * a + b) % PRIME)).cast("string")

    least = [least_hash(a, b) for a, b in least_factors()]
    hashes = F.array(*(F.struct(F.lit(1000 + k).alias("band"), F.concat_ws(",", *least[k * LEAST_ROWS : (k + 1) * LEAST_ROWS]).alias("bucket")) for k in range(LEAST_BANDS)))
    dense = entries.where(F.size(e) >= DENSE_FROM).select(key, F.explode(runs).alias("x"))
    sparse = entries.where(F.size(e) < SPARSE_BELOW).select(key, F.explode(hashes).alias("x"))
    return dense.unionByName(sparse).select(key, "x.band", "x.bucket")


def similarity_of_entries(a: Column, b: Column) -> Column:
    """The share of equal registers among those above 0 in either list of entries."""
    places = lambda c: F.transform(c, lambda x: F.shiftright(x, 6))
    return F.size(F.array_intersect(a, b)) / F.size(F.array_union(places(a), places(b)))


def classes(r1: DataFrame, key: str) -> DataFrame:
    """(key, class_id): keys with the same registers; the class is named after its least key."""
    signature = r1.groupBy(key).agg(F.md5(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("idx", "reg"))), lambda x: F.concat_ws(":", x["idx"].cast("string"), x["reg"].cast("string"))), ",")).alias("signature"))
    least = signature.groupBy("signature").agg(F.min(key).alias("class_id"))
    return signature.join(least, "signature").select(key, "class_id")


def candidates(entries: DataFrame, key: str, m: int) -> DataFrame:
    """(left_key, right_key): pairs of keys that share a bucket. Give it one key of each class, so that copies form no pairs; pairs then grow with the similar ones alone."""
    own = bands(entries, key, m).select(key, F.xxhash64("band", "bucket").alias("bucket"))
    left, right = (own.select(F.col(key).alias(f"{s}_key"), "bucket") for s in ("left", "right"))
    return left.join(right, "bucket").where("left_key < right_key").select("left_key", "right_key").distinct()


def similar_pairs(entries: DataFrame, pairs: DataFrame, key: str) -> DataFrame:
    """The pairs with their share of equal registers, from ``CUT`` on."""
    one, two = (entries.select(F.col(key).alias(f"{s}_key"), F.col("entries").alias(f"{s}_entries")) for s in ("left", "right"))
    own = pairs.join(one, "left_key").join(two, "right_key")
    return own.select("left_key", "right_key", similarity_of_entries(F.col("left_entries"), F.col("right_entries")).alias("equal")).where(F.col("equal") >= CUT)


def pair_sides(pairs: DataFrame, r1: DataFrame, key: str) -> DataFrame:
    """R1 with left_key, right_key and side for given pairs."""
    one = pairs.join(r1.withColumnRenamed(key, "left_key"), "left_key").select("left_key", "right_key", F.lit(1).alias("side"), "idx", "reg")
    two = pairs.join(r1.withColumnRenamed(key, "right_key"), "right_key").select("left_key", "right_key", F.lit(2).alias("side"), "idx", "reg")
    return one.unionByName(two)
