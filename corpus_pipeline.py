"""From raw documents to packed training sequences, in stages.

Each stage reads what the one before it wrote, works on all of it and passes on
documents with the same columns; the last one returns pieces with their places in sequences.
"""

from __future__ import annotations

import os
import uuid

from pyspark.sql import DataFrame, SparkSession

from regsketch.llm import decontaminate, packing, pii, quality, simhash
from regsketch.llm.queries import tokenizer_path
from regsketch.llm.storage import remove, shared_folder
from regsketch.plans.ship import small_batches

#: Bytes of text that a worker tokenises at once: it works beside a JVM that the stages before have filled.
PACKED_AT_ONCE = 1 << 20


def drop_poor(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier rejects go."""
    small_batches(spark)
    return quality.accepted(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of exact or near copies stays."""
    small_batches(spark)
    return simhash.deduplicated(docs)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a benchmark item in them go."""
    small_batches(spark)
    return decontaminate.clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mask_personal(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data in texts becomes the name of its kind."""
    return pii.mask(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Tokenised documents in sequences of at most 2048 tokens."""
    small_batches(spark)
    return packing.pack(docs, tokenizer_path(), at_once=PACKED_AT_ONCE)


STAGES = [("quality", drop_poor), ("near_duplicates", drop_copies), ("decontamination", drop_leaks), ("personal_data", mask_personal), ("packing", pack)]

#: Trained models and similarity of shingle sets are not for SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each result written to shared storage and read again; what a stage has read is removed once its own result is written."""
    base = os.path.join(shared_folder(spark), f"pipeline-{uuid.uuid4().hex}")
    docs, read = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs.write.parquet(path := f"{base}/{k}-{name}")
            docs = spark.read.parquet(path)
            if read is not None:
                remove(spark, read)
            read = path
    return docs
