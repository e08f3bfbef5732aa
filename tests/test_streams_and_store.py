"""Streams equal batches; the store takes a batch once."""

import pytest
from pyspark.sql import functions as F

from regsketch.functions import estimators as E
from regsketch.operators import sketch as S
from regsketch.plans.spec import SketchSpec
from regsketch.sources.store import SketchStore, read_elements, write_packed
from regsketch.streaming import registers as R

SPEC = SketchSpec(8, 24)


@pytest.fixture(scope="module")
def files(spark, sf, tmp_path_factory):
    """Events in ten files by time, with two of them swapped so that rows come late."""
    events = spark.read.parquet(f"{sf}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type")
    rows = events.orderBy("ts", "event_id").collect()
    folder = tmp_path_factory.mktemp("stream")
    step = -(-len(rows) // 10)
    parts = [rows[i : i + step] for i in range(0, len(rows), step)]
    parts[2], parts[6] = parts[6], parts[2]
    for k, part in enumerate(parts):
        spark.createDataFrame(part, events.schema).coalesce(1).write.mode("append").parquet(str(folder / "in"))
    return str(folder / "in"), events.schema, spark.createDataFrame(rows, events.schema)


def rows(df):
    return sorted(map(tuple, df.collect()), key=repr)


def test_store_by_stream_is_the_batch(spark, files, tmp_path):
    path, schema, events = files
    stream = R.source(spark, path, schema, 2)
    r1 = R.updates(stream, "user_id", ["event_type"], SPEC).groupBy("event_type", "idx").agg(F.max("rank").alias("reg"))
    store = SketchStore(spark, str(tmp_path / "store"), ["event_type"], SPEC)
    R.feed(r1, store, str(tmp_path / "check")).awaitTermination(120)
    want = rows(S.build(events, "user_id", SPEC, ["event_type"]).select("event_type", "idx", "reg"))
    assert rows(store.read().select("event_type", "idx", "reg")) == want
    version = store.latest()[0]
    assert store.update(store.read().limit(1), batch=0) == version  # came before
    store.update(store.read().limit(5))
    assert rows(store.read().select("event_type", "idx", "reg")) == want  # a maximum twice
    with pytest.raises(ValueError):
        SketchStore(spark, str(tmp_path / "store"), ["event_type"], SketchSpec(9, 20)).latest()
    assert SketchStore(spark, str(tmp_path / "none"), [], SPEC).read() is None


def test_windowed_registers_with_a_wide_watermark(spark, files, tmp_path):
    path, schema, events = files
    out = R.windowed_registers(R.source(spark, path, schema, 3), "user_id", "ts", F.window("ts", "1 day"), "40 days", SPEC)
    query = out.writeStream.outputMode("update").format("memory").queryName("windowed").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    query.awaitTermination(120)
    got = spark.table("windowed").groupBy("window_start", "idx").agg(F.max("reg").alias("reg"))
    want = S.build(events.withColumn("window_start", F.window("ts", "1 day")["start"]), "user_id", SPEC, ["window_start"])
    assert rows(got) == rows(want)


def test_late_rows_are_dropped_behind_a_narrow_watermark(spark, files, tmp_path):
    path, schema, events = files
    out = R.windowed_registers(R.source(spark, path, schema, 1), "event_id", "ts", F.window("ts", "1 day"), "1 hour", SPEC)
    query = out.writeStream.outputMode("append").format("memory").queryName("late").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    query.awaitTermination(180)
    got = spark.table("late").select("window_start", "idx").distinct().count()
    want = S.build(events.withColumn("window_start", F.window("ts", "1 day")["start"]), "event_id", SPEC, ["window_start"]).count()
    assert 0 < got < want


def test_early_abort_state(spark, files, tmp_path):
    path, schema, events = files
    out = R.early_abort(R.source(spark, path, schema, 4), "user_id", ["event_type"], SPEC)
    query = out.writeStream.outputMode("update").format("memory").queryName("abort").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    query.awaitTermination(180)
    last = spark.table("abort").groupBy("event_type").agg(F.min(F.element_at("counts", 1)).alias("empty"))
    want = S.multiplicity(S.build(events, "user_id", SPEC, ["event_type"]), SPEC, ["event_type"]).select("event_type", F.element_at("counts", 1).alias("empty"))
    assert rows(last) == rows(want)


def test_register_state_tracks_counts_and_least():
    import numpy as np

    r = np.random.default_rng(1)
    state = R.RegisterState.empty(3, 10)
    for _ in range(50):
        state.update(r.integers(0, 8, 20), r.geometric(0.5, 20).clip(1, 11))
        assert (np.bincount(state.registers, minlength=12) == state.counts).all() and state.least == state.registers.min()
    assert R.RegisterState.of(state.registers.tobytes(), 10).least == state.least


def test_sources_and_sinks(spark, sf, tmp_path):
    nation = spark.read.parquet(f"{sf}/nation.parquet")
    for kind in ("parquet", "json", "csv", "orc"):
        nation.write.format(kind).option("header", True).save(str(tmp_path / kind))
        got = read_elements(spark, str(tmp_path / kind), kind, nation.schema.simpleString()[7:-1].replace(":", " ") if kind in ("json", "csv") else None, **({"header": "true"} if kind == "csv" else {}))
        assert rows(S.build(got, "n_name", SPEC)) == rows(S.build(nation, "n_name", SPEC))
    r2 = S.pack(S.build(nation, "n_name", SPEC, ["n_regionkey"]), SPEC, ["n_regionkey"], 5)
    write_packed(r2, str(tmp_path / "packed"), ["n_regionkey"])
    back = S.unpack(spark.read.parquet(str(tmp_path / "packed")), ["n_regionkey"], 5)
    want = S.multiplicity(S.build(nation, "n_name", SPEC), SPEC).select(E.ml(F.col("counts"), 8, 24)).first()[0]
    assert S.multiplicity(S.rollup(back, []), SPEC).select(E.ml(F.col("counts"), 8, 24)).first()[0] == pytest.approx(want)
