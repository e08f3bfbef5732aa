"""Sketches as tables: building, merging, reducing, counting values, packing.

R1 is (keys, idx, reg) with the registers above 0; R2 packs a key's registers into bytes; R3 is
(keys, counts), how many registers have each value. Merging is the maximum by
(keys, idx), so Spark's own partial aggregation is the sketch: what is shuffled is at most 2**p small rows
for each key and task, and a hot key is dealt by register.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce as fold

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.hashing import updates
from ..plans.ship import map_arrow, ship
from ..plans.spec import SketchSpec


#: The largest p of which all registers may be broadcast.
BROADCAST_P = 16


def build(df: DataFrame, item: str | list[str], spec: SketchSpec, keys: list[str] | None = None) -> DataFrame:
    """R1 of the elements of ``item`` for each key; rows with a null element are none."""
    keys = keys or []
    return updates(df, item, keys, spec).groupBy(*keys, "idx").agg(F.max("rank").alias("reg"))


def build_by_key(df: DataFrame, item: str | list[str], spec: SketchSpec, keys: list[str]) -> DataFrame:
    """The same for very many keys without hot ones: one exchange by key serves this and every later grouping by key."""
    return updates(df, item, keys, spec).repartition(*keys).groupBy(*keys, "idx").agg(F.max("rank").alias("reg"))


def build_multi_hash(df: DataFrame, item: str, spec: SketchSpec) -> DataFrame:
    """One hash function for each register and every element in all of them: exact but slow, for comparison with small m."""
    rows = df.where(F.col(item).isNotNull()).select(F.col(item).cast("string").alias("x")).withColumn("idx", F.explode(F.sequence(F.lit(0), F.lit(spec.m - 1))))
    if spec.algo == "md5_64":
        word = F.conv(F.substring(F.md5(F.concat(F.col("idx").cast("string"), F.lit(":"), F.col("x"))), 1, 16), 16, -10).cast("bigint")
    else:
        word = F.xxhash64(F.col("idx").cast("bigint"), F.col("x"))
    from ..functions.hashing import rank

    own = SketchSpec(0, spec.q, spec.algo, spec.seed)
    return rows.select("idx", rank(word, own).alias("rank")).groupBy("idx").agg(F.max("rank").alias("reg"))


def build_partitioned(df: DataFrame, item: str, spec: SketchSpec, keys: list[str] | None = None) -> DataFrame:
    """R1 by way of one dense array of registers for each key and task, which is all that is shuffled."""
    keys = keys or []
    rows = updates(df, item, keys, spec)
    m = spec.m

    def dense(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own: dict[tuple, np.ndarray] = {}
        for batch in batches:
            idx, rank = (batch.column(c).to_numpy() for c in ("idx", "rank"))
            frame = pd.DataFrame({k: batch.column(k).to_pandas() for k in keys})
            groups = frame.groupby(keys, dropna=False, sort=False).indices.items() if keys else [((), np.arange(len(idx)))]
            for key, at in groups:
                name = key if isinstance(key, tuple) else (key,)
                registers = own.setdefault(name, np.zeros(m, dtype=np.int8))
                np.maximum.at(registers, idx[at], rank[at])
        if own:
            columns = [pa.array([k[i] for k in own], type=rows_types[i]) for i in range(len(keys))]
            yield pa.RecordBatch.from_arrays([*columns, pa.array([r.tobytes() for r in own.values()])], names=[*keys, "regs"])

    from pyspark.sql.pandas.types import to_arrow_type

    rows_types = [to_arrow_type(rows.schema[k].dataType) for k in keys]
    schema = ", ".join([*(f"`{k}` {rows.schema[k].dataType.simpleString()}" for k in keys), "regs binary"])
    return unpack(map_arrow(rows, dense, schema), keys).groupBy(*keys, "idx").agg(F.max("reg").alias("reg"))


def merge(*sketches: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """The sketch of the union."""
    keys = keys or []
    return fold(lambda a, b: a.unionByName(b), (s.select(*keys, "idx", "reg") for s in sketches)).groupBy(*keys, "idx").agg(F.max("reg").alias("reg"))


def rollup(r1: DataFrame, keep: list[str]) -> DataFrame:
    """Sketches of coarser keys from those of finer ones."""
    return r1.groupBy(*keep, "idx").agg(F.max("reg").alias("reg"))


def reduced_register(idx: Column, reg: Column, spec: SketchSpec, p: int, q: int) -> tuple[Column, Column]:
    """Where a register of ``spec`` goes in the sketch with p and q, and its value there: the address bits given up become the first bits of the rank."""
    spec.reduced(p, q)
    d = spec.p - p
    if d:
        low = idx.bitwiseAND(F.lit((1 << d) - 1))
        bits = low
        for step in (1, 2, 4, 8, 16):
            if step < d:
                bits = bits.bitwiseOR(F.shiftright(bits, step))
        rank = F.when(low == 0, reg + d).otherwise(F.lit(d + 1) - F.bit_count(bits))
    else:
        rank = reg.cast("int")
    return F.shiftright(idx, d), F.least(rank.cast("int"), F.lit(q + 1)).cast("tinyint")


def reduce(r1: DataFrame, spec: SketchSpec, p: int, q: int, keys: list[str] | None = None) -> DataFrame:
    """The sketch that would have been built with p and q; among registers that fall together the largest rank wins, as in a merge."""
    keys = keys or []
    idx, reg = reduced_register(F.col("idx"), F.col("reg"), spec, p, q)
    return r1.select(*keys, idx.alias("idx"), reg.alias("reg")).groupBy(*keys, "idx").agg(F.max("reg").alias("reg"))


def to_bitmap(r1: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """Only whether a register was hit: the sketch with q = 0."""
    return r1.select(*(keys or []), "idx", F.least("reg", F.lit(1).cast("tinyint")).alias("reg"))


def merge_mixed(a: DataFrame, spec_a: SketchSpec, b: DataFrame, spec_b: SketchSpec, keys: list[str] | None = None) -> tuple[DataFrame, SketchSpec]:
    """The union of sketches with different p or q, in the finest spec both can be reduced to."""
    spec = spec_a.common(spec_b)
    return merge(reduce(a, spec_a, spec.p, spec.q, keys), reduce(b, spec_b, spec.p, spec.q, keys), keys=keys), spec


def multiplicity_tall(r1: DataFrame, spec: SketchSpec, keys: list[str] | None = None) -> DataFrame:
    """(keys, k, c) for values that occur; what is not in R1 is 0."""
    keys = keys or []
    seen = r1.groupBy(*keys, F.col("reg").cast("int").alias("k")).agg(F.count(F.lit(1)).alias("c"))
    empty = seen.groupBy(*keys).agg((F.lit(spec.m) - F.sum("c")).alias("c")).where("c > 0").select(*keys, F.lit(0).alias("k"), "c")
    return seen.unionByName(empty)


def multiplicity(r1: DataFrame, spec: SketchSpec, keys: list[str] | None = None) -> DataFrame:
    """R3. Each task counts the values of its own registers, so that one row for each key and task is shuffled, once; a global sketch without rows gives one empty vector."""
    keys = keys or []
    wide = r1.groupBy(*keys).agg(*(F.count(F.when(F.col("reg") == k, 1)).alias(f"_c{k}") for k in range(1, spec.q + 2)))
    return wide.select(*keys, _vector([F.col(f"_c{k}") for k in range(1, spec.q + 2)], spec.m).alias("counts"))


def multiplicity_of_tall(tall: DataFrame, spec: SketchSpec, keys: list[str]) -> DataFrame:
    """R3 from (keys, k, c) of the values above 0."""
    wide = tall.groupBy(*keys).agg(*(F.coalesce(F.sum(F.when(F.col("k") == k, F.col("c"))), F.lit(0).cast("bigint")).alias(f"_c{k}") for k in range(1, spec.q + 2)))
    return wide.select(*keys, _vector([F.col(f"_c{k}") for k in range(1, spec.q + 2)], spec.m).alias("counts"))


def _vector(own: list[Column], m: int) -> Column:
    return F.array(F.lit(m).cast("bigint") - fold(lambda a, b: a + b, own), *own)


def infer_spec(counts: Column) -> tuple[Column, Column]:
    """p and q of a multiplicity vector."""
    return F.round(F.log2(F.aggregate(counts, F.lit(0).cast("bigint"), lambda a, b: a + b).cast("double"))).cast("int"), (F.size(counts) - 2).cast("int")


def append(r1: DataFrame, new: DataFrame, item: str, spec: SketchSpec, *, drop_known: bool = False) -> DataFrame:
    """R1 with the elements of ``new`` too; updates that cannot change a register are left before the shuffle.

    No rank up to the least register can: one number for the driver. With ``drop_known`` the registers, 2**p rows, are broadcast
    and every update that is not above its register goes; sketches of more than 2**BROADCAST_P registers are joined without a broadcast.
    """
    rows = updates(new, item, [], spec).where(F.col("rank") > F.lit(least_register(r1, spec)))
    if drop_known:
        known = r1.withColumnRenamed("reg", "_reg")
        rows = rows.join(F.broadcast(known) if spec.p <= BROADCAST_P else known, "idx", "left").where(F.col("_reg").isNull() | (F.col("rank") > F.col("_reg"))).select("idx", "rank")
    return merge(r1, rows.groupBy("idx").agg(F.max("rank").alias("reg")))


def least_register(r1: DataFrame, spec: SketchSpec) -> int:
    """The smallest register of a global sketch; 0 while any is empty."""
    row = r1.agg(F.count(F.lit(1)).alias("n"), F.min("reg").alias("least")).first()
    return int(row["least"]) if row["n"] == spec.m else 0


def append_pruning(r1: DataFrame, new: DataFrame, item: str, spec: SketchSpec) -> DataFrame:
    """rows_in, rows_kept, k_min of ``append``."""
    least = least_register(r1, spec)
    kept = F.sum((F.col("rank") > least).cast("bigint"))
    return updates(new, item, [], spec).agg(F.count(F.lit(1)).alias("rows_in"), F.coalesce(kept, F.lit(0)).alias("rows_kept")).withColumn("k_min", F.lit(least))


def diff(a: DataFrame, b: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """Registers in which two sketches differ, with both values; none if they are equal."""
    on = [*(keys or []), "idx"]
    left, right = (s.select(*on, F.col("reg").alias(n)) for s, n in ((a, "reg_a"), (b, "reg_b")))
    return left.join(right, on, "full").where(~F.col("reg_a").eqNullSafe(F.col("reg_b")))


def pack(r1: DataFrame, spec: SketchSpec, keys: list[str] | None = None, bits: int = 8) -> DataFrame:
    """R2: keys, p, q, hash, seed, regs, with each register in so many bits (the spec's own number at least)."""
    keys = keys or []
    if bits < spec.bits_per_register or bits > 8:
        raise ValueError(f"registers up to {spec.q + 1} need {spec.bits_per_register} to 8 bits")
    ship(r1.sparkSession)
    m = spec.m

    @F.pandas_udf(T.BinaryType())
    def packed(idx: pd.Series, reg: pd.Series) -> bytes:
        registers = np.zeros(m, dtype=np.uint8)
        registers[idx.to_numpy()] = reg.to_numpy()
        return np.packbits(np.unpackbits(registers[:, None], axis=1)[:, 8 - bits :]).tobytes()

    extra = [F.lit(spec.p).alias("p"), F.lit(spec.q).alias("q"), F.lit(spec.algo).alias("hash"), F.lit(spec.seed).alias("seed")]
    return r1.groupBy(*keys).agg(packed("idx", "reg").alias("regs")).select(*keys, *extra, "regs")


def unpack(r2: DataFrame, keys: list[str] | None = None, bits: int = 8) -> DataFrame:
    """R1 from R2."""
    keys = keys or []
    ship(r2.sparkSession)

    @F.pandas_udf("array<struct<idx:int,reg:tinyint>>")
    def opened(blobs: pd.Series) -> pd.Series:
        out = []
        for blob in blobs:
            flat = np.unpackbits(np.frombuffer(blob, dtype=np.uint8))
            rows = flat[: len(flat) // bits * bits].reshape(-1, bits)
            registers = np.packbits(np.pad(rows, ((0, 0), (8 - bits, 0))), axis=1).ravel()
            at = np.flatnonzero(registers)
            out.append([{"idx": int(i), "reg": int(registers[i])} for i in at])
        return pd.Series(out)

    return r2.select(*keys, F.explode(opened("regs")).alias("x")).select(*keys, "x.idx", "x.reg")


def running(r1: DataFrame, buckets: int, keys: list[str] | None = None) -> DataFrame:
    """R1 by (keys, bucket) made cumulative over buckets 0 to ``buckets`` - 1."""
    from pyspark.sql import Window

    keys = keys or []
    spread = r1.groupBy(*keys, "idx").agg(F.map_from_entries(F.collect_list(F.struct("bucket", "reg"))).alias("by"))  # an entry for each bucket at most
    full = spread.select(*keys, "idx", "by", F.explode(F.sequence(F.lit(0), F.lit(buckets - 1))).alias("bucket")).select(*keys, "idx", "bucket", F.try_element_at("by", F.col("bucket")).alias("reg"))
    upto = F.max("reg").over(Window.partitionBy(*keys, "idx").orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0))
    return full.withColumn("reg", upto).where("reg is not null").select(*keys, "bucket", "idx", "reg")


#: A last grid value that every number is below, so that the last snapshot is the whole table.
WHOLE = 1 << 62


def grid_bucket(order: Column, grid: list[int]) -> Column:
    """The number of the first grid value above ``order``; null beyond the last (WHOLE is above all)."""
    return fold(lambda c, k: F.when(order < grid[k], F.lit(k)).otherwise(c), range(len(grid) - 1, -1, -1), F.lit(None).cast("int"))


def snapshots(df: DataFrame, item: str, order: str, grid: list[int], spec: SketchSpec) -> DataFrame:
    """(bucket, idx, reg) of the sketch over all rows with ``order`` below each grid value, in one pass: bucket maxima, then running ones."""
    own = build(df.withColumn("bucket", grid_bucket(F.col(order), grid)).where("bucket is not null"), item, spec, ["bucket"])
    return running(own, len(grid))
