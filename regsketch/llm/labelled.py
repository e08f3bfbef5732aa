"""Bounded samples of labelled documents, and their one-task training."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def remainder(modulus: int, column: str = "doc_id"):
    """crc32 of the id as text, modulo; null ids have none."""
    return F.crc32(F.col(column).cast("string")) % modulus


def sample(docs: DataFrame, labels: DataFrame, label: str, modulus: int, held_out: int, most: int) -> DataFrame:
    """(doc_id, text, y) of at most ``most`` labelled documents, at most half of them of either class, by a hash of the id; none of the held-out remainder.

    Labels other than 0 and 1 and ids with contradicting labels are left out.
    """
    usable = labels.where(F.col(label).isin(0, 1) & F.col("doc_id").isNotNull() & (remainder(modulus) != held_out))
    one = usable.groupBy(F.col("doc_id").cast("bigint").alias("doc_id")).agg(F.min(label).alias("y"), F.max(label).alias("other")).where("y = other")
    parts = [one.where(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most // 2) for y in (0, 1)]
    chosen = parts[0].unionByName(parts[1]).select("doc_id", "y")  # at most ``most`` rows of two numbers
    text = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    return text.join(F.broadcast(chosen), "doc_id")


def shares(labels: DataFrame, label: str, modulus: int, held_out: int) -> float:
    """The share of label 1 among all labels that may be learnt from; one half if there are none."""
    row = labels.where(F.col(label).isin(0, 1) & (remainder(modulus) != held_out)).agg(F.avg(F.col(label).cast("double")).alias("share")).first()
    return 0.5 if row["share"] is None else min(0.999, max(0.001, row["share"]))
