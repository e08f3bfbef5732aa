"""Sketches as tables: laws, reductions, packing, nulls, plans."""

import pytest
from pyspark.sql import functions as F

from regsketch import sql
from regsketch.engine import RegSketch
from regsketch.functions import estimators as E
from regsketch.functions import model
from regsketch.operators import joint as J
from regsketch.operators import metrics, simulate
from regsketch.operators import sketch as S
from regsketch.plans import planner
from regsketch.plans.spec import SketchSpec

SPEC = SketchSpec(8, 24)


@pytest.fixture(scope="module")
def line(spark, sf):
    return spark.read.parquet(f"{sf}/lineitem.parquet").select("l_orderkey", "l_partkey", "l_returnflag", "l_extendedprice", "l_shipdate")


def rows(df):
    return sorted(map(tuple, df.collect()), key=repr)


def test_merge_laws(line):
    a, b, c = (S.build(line.where(F.col("l_returnflag") == f), "l_orderkey", SPEC) for f in "ANR")
    whole = rows(S.build(line, "l_orderkey", SPEC))
    assert rows(S.merge(a, b, c)) == rows(S.merge(S.merge(c, a), b)) == whole
    assert rows(S.merge(a, a)) == rows(a) and rows(S.merge(a, a.limit(0))) == rows(a)
    assert rows(S.build(line.union(line).repartition(7), "l_orderkey", SPEC)) == whole


@pytest.mark.parametrize("p,q", [(8, 10), (6, 26), (4, 3), (8, 0), (0, 12)])
def test_reduction_is_a_direct_build(line, p, q):
    assert rows(S.reduce(S.build(line, "l_orderkey", SPEC), SPEC, p, q)) == rows(S.build(line, "l_orderkey", SketchSpec(p, q)))


@pytest.mark.parametrize("bits", [5, 6, 8])
def test_packing_round_trip(line, bits):
    r1 = S.build(line, "l_orderkey", SPEC, ["l_returnflag"])
    r2 = S.pack(r1, SPEC, ["l_returnflag"], bits)
    assert all(len(r["regs"]) == 256 * bits // 8 for r in r2.collect())
    assert rows(S.unpack(r2, ["l_returnflag"], bits).select("l_returnflag", "idx", "reg")) == rows(r1.select("l_returnflag", "idx", "reg"))


def test_partitioned_and_by_key_builds_agree(line):
    want = rows(S.build(line, "l_partkey", SPEC, ["l_returnflag"]))
    assert rows(S.build_partitioned(line, "l_partkey", SPEC, ["l_returnflag"])) == want
    assert rows(S.build_by_key(line, "l_partkey", SPEC, ["l_returnflag"])) == want
    assert rows(S.build_partitioned(line, "l_partkey", SPEC)) == rows(S.build(line, "l_partkey", SPEC))


def test_nulls_and_odd_values(spark):
    df = spark.createDataFrame([(1, 0.0), (2, -0.0), (3, None), (None, float("nan")), (5, float("nan"))], "k int, x double")
    assert S.build(df, "x", SketchSpec(12, 20)).count() == 2  # zero and NaN
    assert S.build(df, ["k", "x"], SketchSpec(12, 20)).count() == 3
    none = df.where("k > 100")
    assert S.build(none, "x", SPEC).count() == 0
    assert RegSketch(spark).approx_distinct(df.withColumn("g", F.when(F.col("k") == 3, "a").otherwise("b")), "x", ["g"]).where("g = 'a'").first()["estimate"] == 0
    maps = spark.sql("SELECT map('a', 1, 'b', 2) AS m UNION ALL SELECT map('b', 2, 'a', 1)")
    assert S.build(maps, "m", SPEC).count() == 1


def test_append_is_a_rebuild(line):
    old, new = line.where("l_orderkey % 3 > 0"), line.where("l_orderkey % 3 = 0")
    spec = SketchSpec(4, 20)
    r1 = S.build(old, "l_orderkey", spec)
    want = rows(S.build(line, "l_orderkey", spec))
    assert rows(S.append(r1, new, "l_orderkey", spec)) == rows(S.append(r1, new, "l_orderkey", spec, drop_known=True)) == want
    kept = S.append_pruning(r1, new, "l_orderkey", spec).first()
    assert kept["k_min"] > 0 and kept["rows_kept"] < kept["rows_in"]


def test_estimates_are_near_the_truth(spark, line):
    exact = line.select("l_orderkey").distinct().count()
    for method in ("corrected_raw", "ml", "original_64", "corrected_raw_table"):
        e = RegSketch(spark, SketchSpec(12, 20)).approx_distinct(line, "l_orderkey", method=method).first()["estimate"]
        assert abs(e / exact - 1) < 4 * metrics.expected_stdev(4096)
    with pytest.raises(ValueError):
        E.original(F.col("c"), 12, 52)
    with pytest.raises(ValueError):
        E.estimate("nothing", F.col("c"), 12, 20)


def test_bounds_hold_the_estimate(line):
    spec = SketchSpec(8, 24)
    v = S.multiplicity(S.build(line, "l_partkey", spec, ["l_returnflag"]), spec, ["l_returnflag"])
    c = F.col("counts")
    for r in v.select(E.ml(c, 8, 24, 1e-12).alias("ml"), *(x.alias(k) for k, x in E.ml_bounds(c, 8, 24).items())).collect():
        assert max(r["lo_weak"], r["lo_strong"]) <= r["ml"] * (1 + 1e-9) and r["ml"] <= min(r["hi_strong"], r["hi_weak"]) * (1 + 1e-9)


def test_saturated_and_empty_vectors(spark):
    df = spark.createDataFrame([([16, 0, 0, 0],), ([0, 0, 0, 16],), ([0, 8, 8, 0],)], "counts array<bigint>")
    c = F.col("counts")
    got = [tuple(r) for r in df.select(E.corrected_raw(c, 4, 2), E.ml(c, 4, 2), E.linear(c, 4), E.raw(c, 4, 2)).collect()]
    assert got[0][:3] == (0, 0, 0) and got[1][:3] == (float("inf"), float("inf"), None) and got[2][2] is None and got[2][0] == pytest.approx(got[2][3])


def test_snapshots_never_fall(line):
    grid = list(range(100, 1600, 50))
    v = S.multiplicity(S.snapshots(line, "l_orderkey", "l_orderkey", grid, SPEC), SPEC, ["bucket"])
    got = [r["e"] for r in v.select("bucket", E.ml(F.col("counts"), 8, 24, 1e-12).alias("e")).orderBy("bucket").collect()]
    assert all(b >= a * (1 - 1e-12) for a, b in zip(got, got[1:]))


def test_simulated_vectors(spark):
    drawn = simulate.draw_registers(spark, 10_000, SketchSpec(10, 22), 20)
    assert all(sum(r["counts"]) == 1024 for r in drawn.collect())
    one = drawn.limit(1)
    dealt = simulate.shuffle_registers(one, 10)
    assert dealt.select("idx").distinct().count() == dealt.count()
    assert S.multiplicity(dealt, SketchSpec(10, 22)).first()["counts"] == one.first()["counts"]


def test_ripple_stays_near_one(spark):
    worst = spark.range(200).select(F.max(F.abs(model.ripple(F.col("id") / F.lit(200.0)) - 1))).first()[0]
    assert 9.8e-6 < worst < 9.885e-6


def test_helper_forms_agree(spark):
    got = spark.range(1, 100).select((F.col("id") / F.lit(7.0)).alias("x")).select(model.h_exact(F.col("x")).alias("a"), model.h_ladder(F.col("x")).alias("b")).collect()
    assert all(r["a"] == pytest.approx(r["b"], rel=1e-9) for r in got)


def test_facade_set_ops(spark, line):
    rs = RegSketch(spark, SketchSpec(12, 20))
    low, high = F.col("l_orderkey") < 1000, F.col("l_orderkey") > 500
    for solver in ("bfgs", "fixed_point"):
        r = rs.set_ops_where(line, "l_orderkey", low, high, solver).first()
        both = line.where(low & high).select("l_orderkey").distinct().count()
        assert abs(r["both"] - both) < 60 and 0 < r["jaccard"] < 1
    r = rs.set_ops(line.where(low), line.where(high), "l_orderkey").first()
    assert abs(r["union"] - line.select("l_orderkey").distinct().count()) < 100


def test_pair_pmf_sums_to_one(spark):
    grid = spark.range(8 * 8).select((F.col("id") % 8).cast("int").alias("k1"), (F.col("id") / 8).cast("int").alias("k2"))
    total = grid.select(J.pair_pmf(F.col("k1"), F.col("k2"), F.lit(50.0), F.lit(80.0), F.lit(20.0), 16, 6).alias("p")).agg(F.sum("p"), F.min("p")).first()
    assert total[0] == pytest.approx(1) and total[1] >= 0


def test_one_scan_serves_all_specs(line):
    specs = [SketchSpec(8, 10), SketchSpec(6, 20)]
    for spec, r1 in planner.build_all(line, "l_orderkey", specs).items():
        assert rows(r1) == rows(S.build(line, "l_orderkey", spec))
    assert planner.choose_build(1, 1.0, 100, SPEC).name == "by_register"
    assert planner.choose_build(10**9, 1e-6, 1000, SPEC).name == "by_key"
    assert planner.choose_build(10, 0.5, 800_000, SketchSpec(12, 20)).name == "partitioned"
    n, share = planner.measure(line, ["l_returnflag"], 0.5)
    assert n == 3 and 0.2 < share < 0.6


def test_plans(line):
    """The build reads one column, combines before its one exchange and stays out of Python."""
    plan = S.build(line, "l_orderkey", SPEC)._jdf.queryExecution().toString()
    assert "ReadSchema: struct<l_orderkey:bigint>" in plan and "IsNotNull(l_orderkey)" in plan
    physical = plan.split("== Physical Plan ==")[1]
    assert physical.count("Exchange hashpartitioning") == 1 and "partial_max" in physical and "Python" not in physical
    vector = S.multiplicity(S.build_by_key(line, "l_partkey", SPEC, ["l_returnflag"]), SPEC, ["l_returnflag"])
    assert vector._jdf.queryExecution().toString().split("== Physical Plan ==")[1].count("Exchange hashpartitioning") == 1


def test_shuffled_rows_are_bounded(spark, line):
    """What is shuffled is at most 2**p rows for each key and task."""
    r1 = S.build(line.repartition(5), "l_partkey", SketchSpec(4, 20), ["l_returnflag"])
    assert r1.count() <= 16 * 3


def test_sql_aggregates_and_table_function(spark, line):
    sql.register(spark)
    line.createOrReplaceTempView("line_view")
    blobs = spark.sql("SELECT l_returnflag, rs_sketch(rs_address(h, 8), rs_rank(h, 8, 24), 256) AS regs FROM (SELECT l_returnflag, xxhash64(l_orderkey) AS h FROM line_view) GROUP BY l_returnflag")
    blobs.createOrReplaceTempView("blobs")
    merged = spark.sql("SELECT idx, CAST(reg AS TINYINT) AS reg FROM (SELECT rs_merge(regs) AS regs FROM blobs) t, LATERAL rs_registers(t.regs)")
    assert rows(merged) == rows(S.build(line, "l_orderkey", SPEC))
