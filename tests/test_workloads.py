"""Experiments and queries that SQL cannot express, against what is known of them."""

import math
from functools import reduce

import pytest
from pyspark.sql import functions as F

from regsketch.operators import metrics, simulate
from regsketch.operators import sketch as S
from regsketch.plans import catalog, queries_work
from regsketch.plans.lineage import cut
from regsketch.plans.spec import SketchSpec

Q = catalog.queries()


def exact_groups(spark, sf):
    line = spark.read.parquet(f"{sf}/lineitem.parquet")
    return {(r[0], r[1]): r[2] for r in line.groupBy("l_returnflag", "l_linestatus").agg(F.countDistinct("l_orderkey")).collect()}


@pytest.mark.parametrize("name, within", [("spark_approx_count_distinct", 0.06), ("spark_hll", 0.06), ("spark_theta", 0.06), ("est_truncated_geometric", 0.2), ("bias_corrected_raw", 0.06)])
def test_estimates_are_near_the_exact_counts(spark, name, within):
    sf = "/root/testdata/sf0.01"
    exact = exact_groups(spark, sf)
    rows = Q[name](spark, sf).collect()
    assert {(r["l_returnflag"], r["l_linestatus"]) for r in rows} == exact.keys()
    for r in rows:
        assert abs(r["estimate"] / exact[r["l_returnflag"], r["l_linestatus"]] - 1) < within


def test_vectors_by_label_are_counted(spark):
    sf = "/root/testdata/sf0.01"
    exact = {r[0]: r[1] for r in spark.read.parquet(f"{sf}/embeddings.parquet").groupBy("label").agg(F.countDistinct("embedding")).collect()}
    got = {r["label"]: r["estimate"] for r in Q["distinct_vectors_by_label"](spark, sf).collect()}
    assert got.keys() == exact.keys() and all(abs(got[k] / exact[k] - 1) < 0.06 for k in exact)


def test_rounds_of_the_likelihood_search(spark, sf):
    rows = Q["est_ml_iterations"](spark, sf).collect()
    column = next(c for c in rows[0].asDict() if "iter" in c or "round" in c)
    assert len(rows) == 6 and all(1 <= r[column] <= 3 for r in rows)


def test_all_pairs_beside_their_exact_sizes(spark):
    """All eight pairs, contained and disjoint ones too: within five standard errors of the union's size."""
    rows = {r["pair"]: r for r in Q["set_ops_all_pairs"](spark, "/root/testdata/sf0.01").collect()}
    assert sorted(rows) == [f"S{k}" for k in range(1, 9)]
    for r in rows.values():
        union = r["exact_only_left"] + r["exact_only_right"] + r["exact_both"]
        assert all(abs(r[c] - r[f"exact_{c}"]) < 5 * 0.0163 * union for c in ("only_left", "only_right", "both")) and r["identifiable"]
    for pair in ("S4", "S8"):
        assert rows[pair]["only_right"] < 1e-3


def test_joint_estimates_beat_inclusion_exclusion_in_every_setting(spark):
    """Ratios of errors above 1 within sampling error for all four sizes at both shapes, and over 2 where little is shared."""
    rows = [r for p, q, runs in ((12, 52, 300), (18, 46, 40)) for r in simulate.joint_error_grid(simulate.joint_samples(spark, SketchSpec(p, q), runs)).select(F.lit(p).alias("p"), "*").collect()]
    assert len(rows) == 2 * 4 * len(simulate.JOINT_GRID)
    for r in rows:
        noise = 2.0 / math.sqrt(r["runs"])
        assert r["factor"] is None or r["factor"] > 1 - noise * 0.5, r
        tolerance = 5 * max(r["stdev_joint"], 1e-9) / math.sqrt(r["runs"]) + 0.003 * (r["truth"] + 1)
        assert abs(r["mean_joint"] - r["truth"]) < tolerance + (r["rmse_joint"] if r["truth"] == 0 else 0), r
        assert 0 <= r["iterations"] < 60
    ratio = {(r["p"], r["config"], r["target"]): r["factor"] for r in rows}
    assert ratio[12, "1000000,1000000,100000", "both"] > 2 and ratio[12, "100000,100000,1000", "both"] > 2


def simulated(spark, shapes, sizes, runs):
    parts = [simulate.error_samples(spark, SketchSpec(p, q), list(sizes), runs).select(F.lit(p).alias("p"), F.lit(q).alias("q"), "*") for p, q in shapes]
    return reduce(lambda a, b: a.unionByName(b), parts)


def test_errors_of_six_shapes_over_all_sizes(spark):
    """Unbiased wherever the shape reaches, the expected spread in the middle, and a likelihood estimate that spreads no more than the corrected mean."""
    errors, by = cut(simulated(spark, queries_work.CONFIGS, (10, 1000, 30_000, 10**6, 10**8, 4 * 10**9, 5 * 10**10), 200)), ["p", "q", "method", "n"]
    rows = {(r["p"], r["q"], r["method"], r["n"]): r for r in metrics.summary(errors, by).join(metrics.bands(errors, by), by).collect()}
    assert len(rows) == 6 * 2 * 7
    reach = {(12, 20): 4 * 10**9, (8, 24): 4 * 10**9, (16, 16): 4 * 10**9, (22, 10): 4 * 10**9, (12, 52): 5 * 10**10, (12, 14): 10**8}
    for (p, q, method, n), r in rows.items():
        scale = metrics.expected_stdev(1 << p)
        if n <= reach[p, q] / 4:
            assert abs(r["bias"]) < 5 * max(r["stdev"], 1e-12) / math.sqrt(200) + 0.1 * scale * scale + 1e-4, (p, q, method, n, r)
            if n >= 1000:  # among fewer elements one rare collision makes all of the spread
                assert r["stdev"] < 1.3 * scale
            assert r["q05"] <= r["q25"] <= r["median"] <= r["q75"] <= r["q95"]
            if method == "ml" and n >= 1000:
                assert r["stdev"] < 1.1 * rows[p, q, "corrected_raw", n]["stdev"] + 1e-9
    assert abs(rows[12, 52, "ml", 5 * 10**10]["bias"]) < 0.01 and abs(rows[12, 52, "corrected_raw", 5 * 10**10]["bias"]) < 0.01


def test_operating_ranges(spark):
    """Some 4e9 for 5-bit registers, 1e8 for 4-bit ones, and no end up to 1e11 for 6-bit ones."""
    errors, by = simulated(spark, ((12, 20), (12, 14), (12, 52)), [int(10 ** (k / 8)) for k in range(24, 89)], 250), ["p", "q", "method"]
    reach = {(r["p"], r["q"], r["method"]): r["up_to"] for r in metrics.operating_range(cut(metrics.summary(errors, [*by, "n"])), by, 0.03).collect()}
    for method in ("corrected_raw", "ml"):
        assert 2e9 <= reach[12, 20, method] <= 5e10 and 4e7 <= reach[12, 14, method] <= 1e9 and reach[12, 52, method] == 10**11


def test_spread_of_estimators_beside_the_trained_one(spark, sf):
    rows = {(r["method"], r["bucket"]): r for r in Q["stdev_comparison_trained"](spark, sf).collect()}
    methods = {m for m, _ in rows}
    assert {"bias_corrected", "ml", "corrected_raw", "raw", "linear", "original"} <= methods
    last = max(b for _, b in rows)
    assert all(rows[m, last]["rmse"] < 0.05 for m in ("bias_corrected", "ml", "corrected_raw", "original"))


def test_bias_table_leaves_no_bias(spark):
    """Within the table's range the corrected mean of drawn sketches is that many elements, to less than the table's own noise and theirs."""
    from regsketch.operators.baselines import bias_corrected

    for n in (5000, 10_000, 20_000):
        drawn = simulate.draw_registers(spark, n, SketchSpec(12, 20), 400, seed=5)
        got = drawn.select(F.avg(bias_corrected(F.col("counts"), 12, 20)).alias("e")).first()["e"]
        assert abs(got / n - 1) < 5 * 0.0163 / 20


def test_snapshots_end_with_the_whole_table(spark, sf):
    line = spark.read.parquet(f"{sf}/lineitem.parquet")
    spec = SketchSpec(12, 20, "md5_64")
    whole = S.multiplicity(S.build(line, "l_orderkey", spec), spec).first()["counts"]
    last = S.multiplicity(S.snapshots(line, "l_orderkey", "l_orderkey", [100, S.WHOLE], spec), spec, ["bucket"]).where("bucket = 1").first()["counts"]
    assert whole == last


def test_joint_errors_over_parts_of_the_pairs(spark, monkeypatch):
    """The parts' exact sizes add up to the pairs', and the joint estimate is no worse within sampling error."""
    sf = "/root/testdata/sf0.01"
    monkeypatch.setattr(queries_work, "JOINT_RUNS", (((12, 20), 100), ((14, 20), 20)))
    exact = {r["pair"]: r for r in Q["exact_set_ops"](spark, sf).collect()}
    rows = Q["joint_error_grid"](spark, sf).collect()
    assert len(rows) == 2 * 4 * len(exact)
    for r in rows:
        own = exact[r["config"]]
        whole = own[r["target"]] if r["target"] != "union" else own["only_left"] + own["only_right"] + own["both"]
        assert abs(r["truth"] * r["runs"] - whole) < 1e-6 * (whole + 1)
        assert r["factor"] is None or r["rmse_joint"] < 1.25 * r["rmse_conventional"] + 0.05


def test_errors_over_parts_of_the_orders(spark):
    """Every order is in one part of each division, and the estimates are unbiased with the shape's spread at most."""
    sf = "/root/testdata/sf0.01"
    orders = spark.read.parquet(f"{sf}/orders.parquet").select("o_orderkey").distinct().count()
    rows = Q["simulated_errors"](spark, sf).collect()
    assert len(rows) == 6 * 2 * len(queries_work.PARTS)
    for r in rows:
        scale = metrics.expected_stdev(1 << r["p"])
        assert round(r["n"] * r["runs"]) == orders
        assert abs(r["bias"]) < 5 * r["stdev"] / math.sqrt(r["runs"]) + scale * scale + 1e-3, r
        assert r["q05"] <= r["q25"] <= r["median"] <= r["q75"] <= r["q95"] and (r["runs"] > 100 or r["stdev"] < 2 * scale)


def test_operating_ranges_over_the_orders(spark):
    """The smallest range ends within the table, the others do not."""
    sf = "/root/testdata/sf0.1"
    whole = spark.read.parquet(f"{sf}/lineitem.parquet").select("l_orderkey").distinct().count()
    reach = {(r["p"], r["q"], r["method"]): r["up_to"] for r in Q["operating_range"](spark, sf).collect()}
    for method in ("corrected_raw", "ml"):
        assert 2e4 < reach[12, 2, method] < whole and reach[12, 6, method] == whole and reach[12, 20, method] == whole
