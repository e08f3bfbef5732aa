"""From elements to update records: hash word, address, rank."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.spec import SketchSpec


def present(columns: list[Column]) -> Column:
    """An element counts if none of its columns is null."""
    return reduce(lambda a, b: a & b, (c.isNotNull() for c in columns))


def canonical(df: DataFrame, name: str) -> Column:
    """A column in a form in which equal values hash alike: one zero and one NaN, microseconds, sorted map entries."""
    kind, c = df.schema[name].dataType, F.col(name)
    if isinstance(kind, (T.DoubleType, T.FloatType)):
        return F.when(F.isnan(c), F.lit(float("nan"))).when(c == 0, F.lit(0.0)).otherwise(c)
    if isinstance(kind, T.TimestampType):
        return F.unix_micros(c)
    if isinstance(kind, T.MapType):
        return F.array_sort(F.map_entries(c))
    return c


def hash_word(columns: Column | list[Column], spec: SketchSpec) -> Column:
    """The 64-bit word of an element.

    ``md5_64`` takes the first 16 hexadecimal digits of the md5 of the text form, with the seed in
    front if there is one; SQL engines agree on it. ``xxhash64`` is the fast one.
    """
    columns = columns if isinstance(columns, list) else [columns]
    if spec.algo == "md5_64":
        text = F.concat_ws("\x1f", *(c.cast("string") for c in columns))
        text = F.concat(F.lit(f"{spec.seed}:"), text) if spec.seed else text
        return F.conv(F.substring(F.md5(text), 1, 16), 16, -10).cast("bigint")
    return F.xxhash64(F.lit(spec.seed).cast("bigint"), *columns) if spec.seed else F.xxhash64(*columns)


def address(word: Column, spec: SketchSpec) -> Column:
    """The register's number: the first p bits."""
    return (F.shiftrightunsigned(word, 64 - spec.p) if spec.p else F.lit(0)).cast("int")


def rank(word: Column, spec: SketchSpec) -> Column:
    """The place of the first one among the q bits after the address, q + 1 if there is none."""
    if not spec.q:
        return F.lit(1).cast("tinyint")
    rest = F.shiftrightunsigned(word, 64 - spec.p - spec.q)
    rest = rest.bitwiseAND(F.lit((1 << spec.q) - 1)) if spec.q < 64 else rest
    for step in (1, 2, 4, 8, 16, 32):  # all bits below the first one are set; counting them gives its place
        if step < spec.q:
            rest = rest.bitwiseOR(F.shiftrightunsigned(rest, step))
    return (F.lit(spec.q + 1) - F.bit_count(rest)).cast("tinyint")


def updates(df: DataFrame, item: str | list[str], keys: list[str], spec: SketchSpec) -> DataFrame:
    """keys, idx, rank for every row with an element."""
    names = [item] if isinstance(item, str) else item
    columns = [canonical(df, n) for n in names]
    word = hash_word(columns, spec)
    return df.where(present([F.col(n) for n in names])).select(*keys, word.alias("h")).select(*keys, address(F.col("h"), spec).alias("idx"), rank(F.col("h"), spec).alias("rank"))
