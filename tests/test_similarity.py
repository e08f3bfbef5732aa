"""Registers as a similarity hash, against exact shingle sets."""

import math
import random

import pytest
from pyspark.sql import functions as F

from regsketch.functions.numeric import ALPHA
from regsketch.operators import baselines as B
from regsketch.operators import metrics, simulate
from regsketch.operators import similarity as L
from regsketch.operators import sketch as S
from regsketch.plans import queries_pairs
from regsketch.plans.spec import SketchSpec

SPEC = SketchSpec(8, 20)


def share(a, b):
    """Equal registers among those above 0 in either."""
    one, two = dict(divmod(x, 64) for x in a), dict(divmod(x, 64) for x in b)
    return sum(two.get(k) == v for k, v in one.items()) / len(one.keys() | two.keys())


def test_candidates_hold_the_similar_pairs(spark):
    """Recall at the cut for sets of 5 to 900 elements, sparse and dense sketches."""
    r = random.Random(1)
    sets, n = [], 0
    for k in range(160):
        base = [f"x{r.randrange(10**9)}" for _ in range(r.randrange(5, 60) if k % 2 else r.randrange(60, 900))]
        for keep in (1.0, 0.97, 0.92, 0.86, 0.5):
            sets.append((n, [b if r.random() < keep else f"y{r.randrange(10**9)}" for b in base]))
            n += 1
    df = spark.createDataFrame([(k, x) for k, own in sets for x in own], "key int, x string")
    entries = L.entry_lists(S.build(df, "x", SPEC, ["key"]), "key").cache()
    lists = {r["key"]: r["entries"] for r in entries.collect()}
    pairs = L.candidates(entries, "key", SPEC.m)
    found = {(p["left_key"], p["right_key"]) for p in pairs.collect()}
    similar = {(a, b) for a in lists for b in range(a + 1, n) if share(lists[a], lists[b]) >= L.CUT}
    near = {p for p in similar if share(lists[p[0]], lists[p[1]]) < L.CUT + 0.05}
    assert len(near) > 60 and len(found & near) >= 0.95 * len(near) and len(found & similar) >= 0.97 * len(similar)
    assert len([p for p in found if p[0] // 5 != p[1] // 5]) < 0.001 * n * n
    got = {(p["left_key"], p["right_key"]): p["equal"] for p in L.similar_pairs(entries, pairs, "key").collect()}
    assert got.keys() == found & similar and all(got[p] == pytest.approx(share(lists[p[0]], lists[p[1]])) for p in got)


def test_equal_registers_tell_the_similarity(spark):
    r = random.Random(2)
    base = [f"x{k}" for k in range(3000)]
    df = spark.createDataFrame([(s, x) for s, own in ((1, base), (2, [b if r.random() < 0.9 else f"y{b}" for b in base])) for x in own], "side int, x string").withColumn("pair", F.lit(1))
    got = L.equal_registers(S.build(df, "x", SketchSpec(12, 20), ["pair", "side"]), SketchSpec(12, 20), ["pair"]).select(L.jaccard_from_equal(F.col("equal"))).first()[0]
    assert abs(got - 0.82) < 0.08


def test_near_duplicate_documents_against_all_pairs(spark):
    """Every pair of classes of sf0.01 compared: what the bands lose at the cut."""
    d = "/root/testdata/sf0.01"
    lists = {r["doc_id"]: r["entries"] for r in queries_pairs._class_entries(spark, d).collect()}
    keys = sorted(lists)
    sets = {k: set(lists[k]) for k in keys}
    similar = {(a, b) for i, a in enumerate(keys) for b in keys[i + 1 :] if 0.8 * len(sets[a]) <= len(sets[b]) <= len(sets[a]) / 0.8 and len(sets[a] & sets[b]) >= 0.6 * len(sets[a]) and share(lists[a], lists[b]) >= L.CUT}
    got = {(r["left_key"], r["right_key"]) for r in queries_pairs.doc_near_duplicates(spark, d).collect()}
    assert got <= similar and len(got) >= 0.95 * len(similar) > 0


def test_classes_of_equal_sketches(spark):
    df = spark.createDataFrame([(1, "a"), (1, "b"), (2, "b"), (2, "a"), (2, "a"), (3, "c")], "key int, x string")
    got = {r["key"]: r["class_id"] for r in L.classes(S.build(df, "x", SPEC, ["key"]), "key").collect()}
    assert got == {1: 1, 2: 1, 3: 3}


def test_bounds_and_their_inverses(spark):
    grid = spark.range(1, 20).select((F.col("id") / F.lit(20.0)).alias("d"))
    low, high = L.equal_bounds(F.col("d"))
    for r in grid.select("d", low.alias("lo"), high.alias("hi")).select("d", "lo", "hi", *(c.alias(n) for n, c in zip("ab", L.distance_interval(F.col("lo")))), *(c.alias(n) for n, c in zip("cd_", L.distance_interval(F.col("hi"))) if n != "d")).collect():
        assert r["lo"] <= r["hi"] and r["a"] == pytest.approx(r["d"]) and abs(r["lo"] - (1 - ALPHA * r["d"])) < 0.35


def test_sum_of_double_exponentials_is_a_log_ratio():
    """The approximation behind the share of equal registers."""
    for a, b in ((1.0, 2.0), (3.0, 40.0), (0.5, 0.6)):
        total = sum(math.exp(-b * 2.0**-k) - math.exp(-a * 2.0**-k) for k in range(-60, 60))
        assert total == pytest.approx(-math.log2(b / a), abs=3e-5)


def test_storage_factors(spark):
    kinds = ((32.0, 1.0, 6.72), (1.0, 0.5, 0.51), (6.0, ALPHA, 1.9553))
    for bits, slope, want in kinds:
        got = spark.range(1).select(metrics.storage_factor(F.lit(bits), F.lit(0.3), F.lit(slope))).first()[0]
        assert got == pytest.approx(want, rel=1e-3)


def test_ordered_baselines_are_near(spark):
    df = spark.range(30_000).select((F.col("id") % 20_000).alias("x"), F.col("id").alias("at"), (F.col("id") % 2).alias("g"))
    for found in (B.hip(df, "x", "at", ["g"], SketchSpec(10, 30)), B.self_learning_bitmap(df, "x", "at", ["g"])):
        for r in found.collect():
            assert abs(r["estimate"] / 10_000 - 1) < 0.1


def test_truncation_and_bias_tables_come_from_fixed_seeds():
    assert simulate.truncation_factor() == simulate.truncation_factor.__wrapped__()
    curve = simulate.bias_curve()
    assert all(a[0] < b[0] for a, b in zip(curve, curve[1:])) and abs(curve[-1][1]) < abs(curve[0][1])


def test_operating_range_ends_where_the_bias_does(spark):
    rows = [("m", 10, 0.001), ("m", 100, 0.02), ("m", 1000, 0.2), ("m", 10_000, 0.001), ("n", 10, 0.0)]
    got = {r["method"]: r["up_to"] for r in metrics.operating_range(spark.createDataFrame(rows, "method string, n bigint, bias double"), ["method"], 0.05).collect()}
    assert got == {"m": 100, "n": 10}
