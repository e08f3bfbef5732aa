"""Sketches over streams.

``windowed_registers`` is the declarative form: registers by window, key and address, kept in Spark's state store, at most 2**p small
rows for each window and key. ``early_abort`` keeps a whole sketch for each key with its value counts and least register, so that
most updates are dropped by one comparison. ``feed`` merges either into a store.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.hashing import updates
from ..plans.ship import ship
from ..plans.spec import SketchSpec
from ..sources.store import SketchStore


def source(spark: SparkSession, path: str, schema, files_per_trigger: int = 1, kind: str = "parquet") -> DataFrame:
    """A stream of the files that come into a folder."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).format(kind).load(path)


def windowed_registers(stream: DataFrame, item: str, time: str, window: Column, watermark: str, spec: SketchSpec, keys: list[str] | None = None) -> DataFrame:
    """R1 by window_start, window_end and keys; rows later than the watermark are dropped."""
    keys = keys or []
    rows = updates(stream.withWatermark(time, watermark).withColumn("_window", window), item, ["_window", *keys], spec)
    return rows.groupBy("_window", *keys, "idx").agg(F.max("rank").alias("reg")).select(F.col("_window.start").alias("window_start"), F.col("_window.end").alias("window_end"), *keys, "idx", "reg")


@dataclass
class RegisterState:
    """Registers, how many have each value, and the least one."""

    registers: np.ndarray
    counts: np.ndarray
    least: int

    @classmethod
    def empty(cls, p: int, q: int) -> RegisterState:
        counts = np.zeros(q + 2, dtype=np.int64)
        counts[0] = 1 << p
        return cls(np.zeros(1 << p, dtype=np.int8), counts, 0)

    @classmethod
    def of(cls, blob: bytes, q: int) -> RegisterState:
        registers = np.frombuffer(blob, dtype=np.int8).copy()
        counts = np.bincount(registers, minlength=q + 2).astype(np.int64)
        return cls(registers, counts, int(np.flatnonzero(counts)[0]))

    def update(self, idx: np.ndarray, rank: np.ndarray) -> int:
        """Take in updates; returns how many registers changed. Ranks up to the least register cannot change any."""
        high = rank > self.least
        idx, rank = idx[high], rank[high]
        changed = 0
        for i, r in zip(idx.tolist(), rank.tolist(), strict=True):
            old = int(self.registers[i])
            if r > old:
                self.counts[old] -= 1
                self.counts[r] += 1
                self.registers[i] = r
                changed += 1
        while not self.counts[self.least]:
            self.least += 1
        return changed


def early_abort(stream: DataFrame, item: str, keys: list[str], spec: SketchSpec) -> DataFrame:
    """(keys, counts, least, changed) after each batch that changed a key's sketch.

    Only the largest rank of each register of a batch reaches a key's state (a partial aggregation would do the same before
    the shuffle in a batch job; in a stream the state function does it).
    """
    ship(stream.sparkSession)
    p, q = spec.p, spec.q

    def run(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        own = RegisterState.of(state.get[0], q) if state.exists else RegisterState.empty(p, q)
        changed = sum(own.update(f["idx"].to_numpy(), f["rank"].to_numpy()) for f in frames)
        if changed or not state.exists:
            state.update((own.registers.tobytes(),))
            yield pd.DataFrame({**{k: [v] for k, v in zip(keys, key, strict=True)}, "counts": [own.counts.tolist()], "least": [own.least], "changed": [changed]})

    rows = updates(stream, item, keys, spec)
    schema = ", ".join([*(f"`{k}` {stream.schema[k].dataType.simpleString()}" for k in keys), "counts array<bigint>, least int, changed int"])
    return rows.groupBy(*keys).applyInPandasWithState(run, schema, "registers binary", "update", GroupStateTimeout.NoTimeout)


def feed(stream: DataFrame, store: SketchStore, checkpoint: str, available_now: bool = True):
    """Merge a stream of R1 rows (update mode) into a store; a batch that comes twice is taken once."""
    columns = [*store.keys, "idx", "reg"]

    def into(batch: DataFrame, number: int) -> None:
        store.update(batch.select(*columns), number)

    writer = stream.writeStream.outputMode("update").foreachBatch(into).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if available_now else writer).start()
