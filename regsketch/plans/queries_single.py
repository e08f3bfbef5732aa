"""Queries on single sketches: construction, model, estimators."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import estimators as E
from ..functions import hashing, model
from ..functions.model import significant
from ..operators import sketch as S
from ..sources.tables import table
from . import oracle as O
from .registry import query
from .spec import SketchSpec

SPEC = SketchSpec(12, 20, "md5_64")
GRP = ["l_returnflag", "l_linestatus"]
LINE = "SELECT l_returnflag, l_linestatus, l_shipdate, l_quantity, l_orderkey AS x FROM lineitem"
LINE_REGS = O.registers(LINE, GRP)
LINE_COUNTS = O.counts(LINE_REGS, GRP)


def lineitem(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem")


def vectors(df: DataFrame, item: str, spec: SketchSpec, keys: list[str]) -> DataFrame:
    return S.multiplicity(S.build(df, item, spec, keys), spec, keys)


def by_group(spark: SparkSession, d: str, spec: SketchSpec = SPEC) -> DataFrame:
    return vectors(lineitem(spark, d), "l_orderkey", spec, GRP)


def _estimates(spark: SparkSession, d: str, e: Column) -> DataFrame:
    return by_group(spark, d).select(*GRP, significant(e).alias("estimate"))


# Construction ---------------------------------------------------------------


@query("hash_words", f"SELECT l_orderkey, CAST(CASE WHEN h >= 9223372036854775808 THEN CAST(h AS HUGEINT) - 18446744073709551616 ELSE h END AS BIGINT) AS h FROM (SELECT DISTINCT l_orderkey, {O.word('l_orderkey')} AS h FROM lineitem)")
def hash_words(spark, d):
    return lineitem(spark, d).select("l_orderkey").distinct().select("l_orderkey", hashing.hash_word(F.col("l_orderkey"), SPEC).alias("h"))


def _xxhash_sql(x: str) -> str:
    """XXH64 with seed 42 of one 8-byte integer, in 128-bit arithmetic modulo 2**64."""
    mask = "18446744073709551615::UHUGEINT"
    mul = lambda a, b: f"((({a}) * {b}::UHUGEINT) & {mask})"
    rot = lambda a, r: f"(((({a}) << {r}) & {mask}) | (({a}) >> {64 - r}))"
    p1, p2, p3, p4, p5 = 11400714785074694791, 14029467366897019727, 1609587929392839161, 9650029242287828579, 2870177450012600261
    return f"""SELECT l_orderkey, CAST(CASE WHEN h >= 9223372036854775808 THEN CAST(h AS HUGEINT) - 18446744073709551616 ELSE CAST(h AS HUGEINT) END AS BIGINT) AS h FROM (
SELECT l_orderkey, xor(g, g >> 32) AS h FROM (SELECT l_orderkey, {mul('xor(f, f >> 29)', p3)} AS g FROM (SELECT l_orderkey, {mul('xor(e, e >> 33)', p2)} AS f FROM (
SELECT l_orderkey, ({mul(rot('c', 27), p1)} + {p4}::UHUGEINT) & {mask} AS e FROM (SELECT l_orderkey, xor({42 + p5 + 8}::UHUGEINT & {mask}, {mul(rot('b', 31), p1)}) AS c FROM (
SELECT l_orderkey, {mul('v', p2)} AS b FROM (SELECT DISTINCT l_orderkey, CAST({x} AS UHUGEINT) AS v FROM lineitem)))))))"""


@query("hash_words_xx", _xxhash_sql("l_orderkey"))
def hash_words_xx(spark, d):
    return lineitem(spark, d).select("l_orderkey").distinct().select("l_orderkey", hashing.hash_word(F.col("l_orderkey"), SketchSpec()).alias("h"))


@query("update_records", f"SELECT l_orderkey, idx, rank FROM ({O.updates('SELECT DISTINCT l_orderkey, l_orderkey AS x FROM lineitem', ['l_orderkey'], 12, 20)})")
def update_records(spark, d):
    return hashing.updates(lineitem(spark, d).select("l_orderkey").distinct(), "l_orderkey", ["l_orderkey"], SPEC)


@query("sketch_registers", O.registers(LINE, []))
def sketch_registers(spark, d):
    return S.build(lineitem(spark, d), "l_orderkey", SPEC)


@query("sketch_registers_grouped", LINE_REGS)
def sketch_registers_grouped(spark, d):
    return S.build(lineitem(spark, d), "l_orderkey", SPEC, GRP)


@query("sketch_registers_by_key", O.registers("SELECT o_custkey, o_orderkey AS x FROM orders", ["o_custkey"], 8, 20))
def sketch_registers_by_key(spark, d):
    """Very many small sketches, one exchange for all that follows."""
    return S.build_by_key(table(spark, d, "orders"), "o_orderkey", SketchSpec(8, 20, "md5_64"), ["o_custkey"])


@query("sketch_registers_partitioned", LINE_REGS)
def sketch_registers_partitioned(spark, d):
    """The same registers by way of dense arrays for each task."""
    return S.build_partitioned(lineitem(spark, d), "l_orderkey", SPEC, GRP)


@query("sketch_packed_round_trip", LINE_REGS)
def sketch_packed_round_trip(spark, d):
    """Registers packed into five bits each, and read back."""
    return S.unpack(S.pack(S.build(lineitem(spark, d), "l_orderkey", SPEC, GRP), SPEC, GRP, 5), GRP, 5)


@query("sketch_filtered", O.registers(f"{LINE} WHERE l_quantity BETWEEN 10 AND 20", []))
def sketch_filtered(spark, d):
    return S.build(lineitem(spark, d).where(F.col("l_quantity").between(10, 20)), "l_orderkey", SPEC)


_MULTI = f"SELECT i::INT AS idx, {O.word('user_id', 'i')} AS h FROM (SELECT DISTINCT user_id FROM events), range(64) t(i)"


@query("sketch_multi_hash", f"SELECT idx, max({O.rank('h', 0, 20)})::TINYINT AS reg FROM ({_MULTI}) GROUP BY idx")
def sketch_multi_hash(spark, d):
    return S.build_multi_hash(table(spark, d, "events").select("user_id").distinct(), "user_id", SketchSpec(6, 20, "md5_64"))


@query("bitmap_registers", O.registers("SELECT user_id AS x FROM events", [], 12, 0))
def bitmap_registers(spark, d):
    """A sketch with q = 0, by reducing one with q = 20 to whether registers were hit."""
    return S.to_bitmap(S.build(table(spark, d, "events"), "user_id", SPEC))


@query("sketch_merge", O.registers(f"{LINE} WHERE l_returnflag IN ('A', 'R')", []))
def sketch_merge(spark, d):
    line = lineitem(spark, d)
    return S.merge(*(S.build(line.where(F.col("l_returnflag") == f), "l_orderkey", SPEC) for f in "AR"))


@query("sketch_merge_mixed", O.registers("SELECT o_orderkey AS x FROM orders UNION ALL SELECT l_orderkey FROM lineitem", [], 10, 22))
def sketch_merge_mixed(spark, d):
    """(12,20) with (10,22): the common spec is (10,22)."""
    other = SketchSpec(10, 22, "md5_64")
    return S.merge_mixed(S.build(table(spark, d, "orders"), "o_orderkey", SPEC), SPEC, S.build(lineitem(spark, d), "l_orderkey", other), other)[0]


@query("sketch_rollup", O.registers(LINE, ["l_returnflag"]))
def sketch_rollup(spark, d):
    return S.rollup(S.build(lineitem(spark, d), "l_orderkey", SPEC, GRP), ["l_returnflag"])


@query("shard_merge", O.registers("SELECT user_id AS x FROM events", []))
def shard_merge(spark, d):
    """Four streams sketched apart, then merged."""
    events = table(spark, d, "events").withColumn("shard", F.pmod(F.xxhash64("event_id"), F.lit(4)))
    return S.rollup(S.build(events, "user_id", SPEC, ["shard"]), [])


@query("sketch_reduce", O.registers(LINE, [], 8, 10))
def sketch_reduce(spark, d):
    return S.reduce(S.build(lineitem(spark, d), "l_orderkey", SPEC), SPEC, 8, 10)


@query("sketch_diff", "SELECT 0::BIGINT AS differing")
def sketch_diff(spark, d):
    """Registers in which a reduced sketch differs from one built so: none."""
    line, small = lineitem(spark, d), SketchSpec(10, 12, "md5_64")
    return S.diff(S.reduce(S.build(line, "l_orderkey", SPEC), SPEC, 10, 12), S.build(line, "l_orderkey", small)).agg(F.count(F.lit(1)).alias("differing"))


_FLAG_REGS = O.registers(LINE, ["l_returnflag"])


@query("multiplicity_tall", f"SELECT l_returnflag, reg::INT AS k, count(*) AS c FROM ({_FLAG_REGS}) GROUP BY l_returnflag, reg UNION ALL SELECT l_returnflag, 0, 4096 - count(*) FROM ({_FLAG_REGS}) GROUP BY l_returnflag HAVING count(*) < 4096")
def multiplicity_tall(spark, d):
    return S.multiplicity_tall(S.build(lineitem(spark, d), "l_orderkey", SPEC, ["l_returnflag"]), SPEC, ["l_returnflag"])


@query("multiplicity_array", f"SELECT l_returnflag, array_to_string(c, ',') AS counts FROM ({O.counts(_FLAG_REGS, ['l_returnflag'])})")
def multiplicity_array(spark, d):
    return vectors(lineitem(spark, d), "l_orderkey", SPEC, ["l_returnflag"]).select("l_returnflag", F.array_join(F.col("counts").cast("array<string>"), ",").alias("counts"))


@query("infer_spec", f"SELECT CAST(round(log2(list_sum(c))) AS INT) AS p, CAST(len(c) - 2 AS INT) AS q FROM ({O.counts(O.registers(LINE, []), [])})")
def infer_spec(spark, d):
    p, q = S.infer_spec(F.col("counts"))
    return vectors(lineitem(spark, d), "l_orderkey", SPEC, []).select(p.alias("p"), q.alias("q"))


_EARLY, _LATE = "l_shipdate < TIMESTAMP '1999-01-01 00:00:00'", "l_shipdate >= TIMESTAMP '1999-01-01 00:00:00'"


@query("sketch_append", O.registers(LINE, [], 8, 20))
def sketch_append(spark, d):
    """A sketch of the earlier rows with the later ones added is the sketch of all."""
    line, spec = lineitem(spark, d), SketchSpec(8, 20, "md5_64")
    return S.append(S.build(line.where(_EARLY), "l_orderkey", spec), line.where(_LATE), "l_orderkey", spec, drop_known=True)


_OLD = O.registers(f"{LINE} WHERE l_shipdate < TIMESTAMP '1999-01-01'", [], 8, 20)
_NEW = O.updates(f"{LINE} WHERE l_shipdate >= TIMESTAMP '1999-01-01'", [], 8, 20)


@query("append_pruning", f"WITH k AS (SELECT CASE WHEN count(*) = 256 THEN min(reg) ELSE 0 END AS k_min FROM ({_OLD})) SELECT count(*) AS rows_in, count(*) FILTER (WHERE rank > k_min) AS rows_kept, any_value(k_min)::INT AS k_min FROM ({_NEW}), k")
def append_pruning(spark, d):
    line, spec = lineitem(spark, d), SketchSpec(8, 20, "md5_64")
    return S.append_pruning(S.build(line.where(_EARLY), "l_orderkey", spec), line.where(_LATE), "l_orderkey", spec)


GRID = [*(4**k for k in range(2, 10)), S.WHOLE]
_SNAP = " UNION ALL ".join(f"SELECT {k} AS bucket, l_orderkey AS x FROM lineitem WHERE l_orderkey < {t}" for k, t in enumerate(GRID))
_SNAP_REGS = O.registers(_SNAP, ["bucket"])


@query("snapshot_multiplicity", f"SELECT bucket, k::INT AS k, c FROM (SELECT bucket, reg AS k, count(*) AS c FROM ({_SNAP_REGS}) GROUP BY bucket, reg UNION ALL SELECT bucket, 0, 4096 - count(*) FROM ({_SNAP_REGS}) GROUP BY bucket HAVING count(*) < 4096)")
def snapshot_multiplicity(spark, d):
    """Value counts of growing prefixes of the keys, from one pass."""
    snaps = S.snapshots(lineitem(spark, d), "l_orderkey", "l_orderkey", GRID, SPEC)
    return S.multiplicity_tall(snaps, SPEC, ["bucket"])


# Model ----------------------------------------------------------------------

_PMF_Q = 6


def _upto(j: str) -> str:
    return f"pow(1 - pow(2.0, -({j})), nu)"


_HITS = f"SELECT count(*) AS nu, max(rank)::INT AS k FROM ({O.updates('SELECT DISTINCT l_orderkey AS x FROM lineitem', [], 12, _PMF_Q)}) GROUP BY idx"
_PMF = f"CASE WHEN nu = 0 THEN CASE WHEN k = 0 THEN 1.0 ELSE 0.0 END WHEN k = 0 THEN 0.0 WHEN k <= {_PMF_Q} THEN {_upto('k')} - CASE WHEN k = 1 THEN 0.0 ELSE {_upto('k - 1')} END ELSE 1 - {_upto(str(_PMF_Q))} END"


@query("register_pmf", f"""WITH hit AS ({_HITS}), seen AS (SELECT nu, k FROM hit UNION ALL SELECT 0, 0 FROM (SELECT count(*) AS n FROM hit), range(4096) t(i) WHERE i < 4096 - n)
SELECT k::INT AS k, nu::INT AS nu, registers, {O.sig('pr')} AS pr FROM (SELECT a.k, n.nu, (SELECT count(*) FROM seen s WHERE s.nu = n.nu AND s.k = a.k) AS registers, ({_PMF.replace('nu', 'n.nu').replace('k', 'a.k')})::DOUBLE AS pr FROM (SELECT DISTINCT nu FROM seen) n, range({_PMF_Q + 2}) a(k))""")
def register_pmf(spark, d):
    """For every number of orders that hit a register: how many such registers have each value, and the chance of it."""
    spec = SketchSpec(12, _PMF_Q, "md5_64")
    hit = hashing.updates(lineitem(spark, d).select("l_orderkey").distinct(), "l_orderkey", [], spec).groupBy("idx").agg(F.count(F.lit(1)).alias("nu"), F.max("rank").cast("int").alias("k"))
    seen = hit.groupBy("nu", "k").agg(F.count(F.lit(1)).alias("c"))
    seen = seen.unionByName(hit.agg((spec.m - F.count(F.lit(1))).alias("c")).where("c > 0").select(F.lit(0).cast("bigint").alias("nu"), F.lit(0).alias("k"), "c"))
    cells = F.array(*(F.coalesce(F.sum(F.when(F.col("k") == k, F.col("c"))), F.lit(0).cast("bigint")) for k in range(_PMF_Q + 2)))
    rows = seen.groupBy(F.col("nu").cast("int").alias("nu")).agg(cells.alias("cells")).select("nu", F.posexplode("cells").alias("k", "registers"))
    return rows.select("k", "nu", "registers", significant(model.register_pmf(F.col("k"), F.col("nu"), _PMF_Q)).alias("pr"))


@query("expected_multiplicity", f"""WITH c AS (SELECT c FROM ({O.counts(O.registers(LINE, []), [])})), n AS (SELECT count(DISTINCT l_orderkey)::DOUBLE AS n FROM lineitem)
SELECT k::INT AS k, c[k + 1] AS observed, {O.sig('4096 * (CASE WHEN k > 20 THEN 1.0 ELSE exp(-n / (4096.0 * pow(2.0, k))) END - CASE WHEN k = 0 THEN 0.0 ELSE exp(-n / (4096.0 * pow(2.0, k - 1))) END)')} AS expected FROM c, n, range(22) t(k)""")
def expected_multiplicity(spark, d):
    """Observed value counts beside those expected of the exact number of elements."""
    line = lineitem(spark, d)
    n = line.agg(F.countDistinct("l_orderkey").cast("double").alias("n"))
    tall = vectors(line, "l_orderkey", SPEC, []).select(F.posexplode("counts").alias("k", "observed")).join(F.broadcast(n))  # one row
    return tall.select("k", "observed", significant(4096 * model.poisson_pmf(F.col("k"), F.col("n"), 4096, 20)).alias("expected"))


_RIPPLE = "list_sum(list_transform(range(-60, 61), lambda k: CASE WHEN pow(2.0, k + (x - floor(x))) > 700 THEN 0.0 ELSE pow(2.0, k + (x - floor(x))) * exp(-pow(2.0, k + (x - floor(x)))) END))"


@query("ripple_curve", f"SELECT n, days, {O.sig('x')} AS x, {O.sig('y')} AS ripple FROM (SELECT n, days, x, ln(2) * {_RIPPLE} AS y FROM (SELECT n, count(*) AS days, log2(n::DOUBLE) AS x FROM (SELECT count(DISTINCT o_orderkey) AS n FROM orders WHERE o_orderkey IS NOT NULL GROUP BY o_orderdate) GROUP BY n))")
def ripple_curve(spark, d):
    """The periodic factor at each number of orders that a day has, of which the binary logarithm counts; it leaves 1 by less than 1e-5."""
    daily = table(spark, d, "orders").where("o_orderkey IS NOT NULL").groupBy("o_orderdate").agg(F.countDistinct("o_orderkey").alias("n"))
    sizes = daily.groupBy("n").agg(F.count(F.lit(1)).alias("days")).withColumn("x", F.log2(F.col("n").cast("double")))
    return sizes.select("n", "days", significant(F.col("x")).alias("x"), significant(model.ripple(F.col("x"))).alias("ripple"))


#: Few registers of a small range, so that prefixes of the keys leave all shares of them empty, and saturate all shares.
FILL = SketchSpec(6, 6, "md5_64")
_LINES = ["l_linenumber", "bucket"]
_FILL_SRC = " UNION ALL ".join(f"SELECT l_linenumber, {k} AS bucket, l_orderkey AS x FROM lineitem WHERE l_orderkey < {t}" for k, t in enumerate(GRID))
_SHARES = f"SELECT l_linenumber, bucket, c[1] / 64.0::DOUBLE AS empty, 1 - c[8] / 64.0::DOUBLE AS below FROM ({O.counts(O.registers(_FILL_SRC, _LINES, 6, 6), _LINES, 6, 6)})"


def shares(spark: SparkSession, d: str) -> DataFrame:
    """(l_linenumber, bucket, empty, below): shares of registers that are empty, and that are not saturated, in the sketch of each line number's orders in each prefix of the keys."""
    rows = lineitem(spark, d).withColumn("bucket", S.grid_bucket(F.col("l_orderkey"), GRID)).where("bucket IS NOT NULL")
    grown = S.running(S.build(rows, "l_orderkey", FILL, _LINES), len(GRID), ["l_linenumber"])
    counts = S.multiplicity(grown, FILL, _LINES)
    return counts.select(*_LINES, (E.count(F.col("counts"), 0) / float(FILL.m)).alias("empty"), (1 - E.count(F.col("counts"), FILL.q + 1) / float(FILL.m)).alias("below"))


@query("fill_functions", f"SELECT l_linenumber, bucket, empty, below, {O.sig(O.low_fill('empty'))} AS low_fill, {O.sig(O.high_fill('below'))} AS high_fill, {O.sig(O.high_fill('below'))} AS high_fill_slow FROM ({_SHARES})")
def fill_functions(spark, d):
    """Both fill functions at the shares of growing sketches; the slow form of the second agrees with the fast one."""
    low, high = F.col("empty"), F.col("below")
    return shares(spark, d).select(*_LINES, "empty", "below", significant(model.low_fill_folded(low, 24)).alias("low_fill"), significant(model.high_fill_folded(high, 30)).alias("high_fill"), significant(model.high_fill_slow(high)).alias("high_fill_slow"))


@query("fill_identity", f"SELECT l_linenumber, bucket, below, {O.sig('CASE WHEN below <= 0 OR below >= 1 THEN 0.0 ELSE ' + O.ALPHA + ' / -ln(below) - ' + O.low_fill('below') + ' END')} AS high_fill_by_log FROM ({_SHARES})")
def fill_identity(spark, d):
    """The second fill function by way of the first and the logarithm, at the shares of growing sketches."""
    return shares(spark, d).select(*_LINES, "below", significant(model.high_fill_by_log(F.col("below"), 20)).alias("high_fill_by_log"))


#: The helper in double precision: a series where the difference would lose digits.
_H = "(CASE WHEN x < 0.01 THEN x / 2 - x * x / 12 + x * x * x * x / 720 WHEN x > 700 THEN 1.0 ELSE 1 - x / (exp(x) - 1) END)"


@query("h_function", f"SELECT l_returnflag, l_linestatus, k::INT AS k, x, {O.sig(_H)} AS h, {O.sig(_H)} AS h_ladder FROM (SELECT l_returnflag, l_linestatus, k, n / (4096.0::DOUBLE * pow(2.0, least(k, 20))) AS x FROM (SELECT l_returnflag, l_linestatus, count(DISTINCT l_orderkey)::DOUBLE AS n FROM lineitem GROUP BY l_returnflag, l_linestatus), range(1, 22) t(k))")
def h_function(spark, d):
    """The likelihood's helper at the arguments that it has for each group's exact number of orders and each register value, exactly, and by a series and doublings."""
    exact = lineitem(spark, d).groupBy(*GRP).agg(F.countDistinct("l_orderkey").cast("double").alias("n"))
    grid = exact.select(*GRP, "n", F.explode(F.sequence(F.lit(1), F.lit(SPEC.q + 1))).alias("k"))
    grid = grid.select(*GRP, "k", (F.col("n") / (float(SPEC.m) * F.pow(F.lit(2.0), F.least("k", F.lit(SPEC.q)).cast("double")))).alias("x"))
    return grid.select(*GRP, "k", "x", significant(model.h_exact(F.col("x"))).alias("h"), significant(model.h_ladder(F.col("x"))).alias("h_ladder"))


# Estimators -----------------------------------------------------------------


def _est(expr: str, source: str = LINE_COUNTS) -> str:
    return f"SELECT l_returnflag, l_linestatus, {O.sig('estimate')} AS estimate FROM (SELECT l_returnflag, l_linestatus, {expr} AS estimate FROM ({source}))"


@query("est_raw", _est(O.raw(12, 20)))
def est_raw(spark, d):
    return _estimates(spark, d, E.raw(F.col("counts"), 12, 20))


@query("est_raw_exact_alpha", _est(O.raw(12, 20, factor=f"{E.alpha(4096)!r}e0")))
def est_raw_exact_alpha(spark, d):
    """With the bias correction of exactly so many registers."""
    return _estimates(spark, d, E.raw(F.col("counts"), 12, 20, E.alpha(4096)))


@query("est_raw_legacy_alpha", _est(O.raw(12, 20, factor=f"{E.legacy_alpha(4096)!r}e0")))
def est_raw_legacy_alpha(spark, d):
    """With the four-digit constant of legacy implementations."""
    return _estimates(spark, d, E.raw(F.col("counts"), 12, 20, E.legacy_alpha(4096)))


@query("est_linear", _est(O.linear(12)))
def est_linear(spark, d):
    return _estimates(spark, d, E.linear(F.col("counts"), 12))


@query("est_large_range", _est(O.large_range(O.raw(12, 20))))
def est_large_range(spark, d):
    return _estimates(spark, d, E.large_range(E.raw(F.col("counts"), 12, 20)))


@query("est_original", _est(O.original(12, 20)))
def est_original(spark, d):
    return _estimates(spark, d, E.original(F.col("counts"), 12, 20))


@query("est_original_64", _est(O.original(12, 20, large=False)))
def est_original_64(spark, d):
    return _estimates(spark, d, E.original_64(F.col("counts"), 12, 20))


@query("est_corrected_raw", _est(O.corrected(12, 20)))
def est_corrected_raw(spark, d):
    return _estimates(spark, d, E.corrected_raw(F.col("counts"), 12, 20))


@query("est_corrected_raw_table", _est(O.corrected(12, 20)))
def est_corrected_raw_table(spark, d):
    """Fill functions looked up instead of computed."""
    return _estimates(spark, d, E.corrected_raw_table(F.col("counts"), 12, 20))


_SKIP = f"({O.ALPHA} * {4096.0**2!r} / (4096.0 * {O.low_fill('(c[1] / 4096.0)')} + {O.middle(20)}))"
_BY_LOG = f"({O.ALPHA} * {4096.0**2!r} / (4096.0 * {O.low_fill('(c[1] / 4096.0)')} + {O.middle(20)} + 4096.0 * (CASE WHEN c[22] = 0 THEN 0.0 ELSE {O.ALPHA} / -ln(1 - c[22] / 4096.0) - {O.low_fill('(1 - c[22] / 4096.0)')} END) * {2.0**-20!r}))"


@query("est_corrected_raw_variants", f"SELECT l_returnflag, l_linestatus, {O.sig('a')} AS skip_high, {O.sig('b')} AS approx_high FROM (SELECT l_returnflag, l_linestatus, {_SKIP} AS a, {_BY_LOG} AS b FROM ({LINE_COUNTS}))")
def est_corrected_raw_variants(spark, d):
    """Without the upper fill function, and with it by the logarithm."""
    c = F.col("counts")
    return by_group(spark, d).select(*GRP, significant(E.corrected_raw(c, 12, 20, skip_high=True)).alias("skip_high"), significant(E.corrected_raw(c, 12, 20, approx_high=True)).alias("approx_high"))


@query("est_geometric", _est(O.geometric(12, 20)))
def est_geometric(spark, d):
    return _estimates(spark, d, E.geometric(F.col("counts"), 12, 20))


@query("est_truncated_geometric", None)
def est_truncated_geometric(spark, d):
    """The mean over the smallest 70 % of the values, with a factor from simulation."""
    from ..operators.simulate import truncation_factor

    return _estimates(spark, d, E.truncated_geometric(F.col("counts"), 12, 20, 0.7, truncation_factor()))


_ML = O.ml_table("ml", LINE_COUNTS, GRP, 12, 20)


@query("est_ml", f"WITH RECURSIVE {_ML} SELECT l_returnflag, l_linestatus, {O.sig('estimate')} AS estimate FROM ml")
def est_ml(spark, d):
    return _estimates(spark, d, E.ml(F.col("counts"), 12, 20, 1e-12))


#: The same with the fast hash, in 128-bit arithmetic on the SQL side.
XX = SketchSpec(12, 20)
_XX_WORDS = f"SELECT l_returnflag, l_linestatus, CAST(CASE WHEN h < 0 THEN CAST(h AS HUGEINT) + 18446744073709551616 ELSE h END AS UBIGINT) AS h FROM lineitem JOIN ({_xxhash_sql('l_orderkey')}) USING (l_orderkey)"
_XX_REGS = f"SELECT l_returnflag, l_linestatus, idx, max(rank)::TINYINT AS reg FROM (SELECT l_returnflag, l_linestatus, {O.address('h', 12)} AS idx, {O.rank('h', 12, 20)} AS rank FROM ({_XX_WORDS})) GROUP BY ALL"
_XX_COUNTS = O.counts(_XX_REGS, GRP)


def _xx_counts(spark: SparkSession, d: str) -> DataFrame:
    return by_group(spark, d, XX)


@query("est_corrected_raw_xx", f"SELECT l_returnflag, l_linestatus, {O.sig('estimate')} AS estimate FROM (SELECT l_returnflag, l_linestatus, {O.corrected(12, 20)} AS estimate FROM ({_XX_COUNTS}))")
def est_corrected_raw_xx(spark, d):
    """Build and corrected estimate as one would use them: the fast hash, fill functions from tables."""
    return _xx_counts(spark, d).select(*GRP, significant(E.corrected_raw_table(F.col("counts"), 12, 20)).alias("estimate"))


@query("est_ml_xx", f"WITH RECURSIVE {O.ml_table('mlx', _XX_COUNTS, GRP, 12, 20)} SELECT l_returnflag, l_linestatus, {O.sig('estimate')} AS estimate FROM mlx")
def est_ml_xx(spark, d):
    """Build and likelihood estimate with the fast hash."""
    return _xx_counts(spark, d).select(*GRP, significant(E.ml(F.col("counts"), 12, 20, 1e-12)).alias("estimate"))


@query("est_ml_newton", f"WITH RECURSIVE {_ML} SELECT l_returnflag, l_linestatus, {O.sig('estimate')} AS estimate FROM ml")
def est_ml_newton(spark, d):
    return _estimates(spark, d, E.ml(F.col("counts"), 12, 20, 1e-12, "newton"))


@query("est_batches", f"WITH RECURSIVE {_ML} SELECT l_returnflag, l_linestatus, {O.sig('c.estimate')} AS corrected_raw, {O.sig('ml.estimate')} AS ml FROM (SELECT l_returnflag, l_linestatus, {O.corrected(12, 20)} AS estimate FROM ({LINE_COUNTS})) c JOIN ml USING (l_returnflag, l_linestatus)")
def est_batches(spark, d):
    """Both estimates in Arrow batches, as for millions of sketches."""
    from ..operators.batches import estimates

    return estimates(by_group(spark, d), epsilon=1e-12).select(*GRP, *(significant(F.col(m)).alias(m) for m in ("corrected_raw", "ml")))


@query("est_ml_iterations")
def est_ml_iterations(spark, d):
    """Rounds of the secant search at the usual tolerance: three at most."""
    trace = E.ml_trace(F.col("counts"), 12, 20)
    return by_group(spark, d).select(*GRP, trace.alias("t")).select(*GRP, significant(F.col("t.estimate")).alias("estimate"), "t.rounds")


_TOP = f"list_max(list_transform(range(0, 22), lambda k: CASE WHEN c[k + 1] > 0 THEN least(k, 20) ELSE 0 END))"
_A, _B, _FULL = f"(c[1] + {O.middle(20)})", f"({O.middle(20)} + c[22] * {2.0**-20!r})", "(4096.0 - c[1])"


@query("ml_bounds", f"""SELECT l_returnflag, l_linestatus, {O.sig('lw')} AS lo_weak, {O.sig('ls')} AS lo_strong, {O.sig('hs')} AS hi_strong, {O.sig('hw')} AS hi_weak FROM (SELECT l_returnflag, l_linestatus,
4096 * f / (a + b / 2) AS lw, 4096 * f / b * ln(1 + b / a) AS ls, 4096 * pow(2.0, top) * ln(1 + f / (pow(2.0, top) * a)) AS hs, 4096 * f / a AS hw FROM (SELECT l_returnflag, l_linestatus, {_A} AS a, {_B} AS b, {_FULL} AS f, {_TOP} AS top FROM ({LINE_COUNTS})))""")
def ml_bounds(spark, d):
    """Bounds of the likelihood estimate from both sides."""
    return by_group(spark, d).select(*GRP, *(significant(v).alias(k) for k, v in E.ml_bounds(F.col("counts"), 12, 20).items()))


@query("ml_error_bound", f"SELECT l_returnflag, l_linestatus, {O.sig('0.005e0 * (1 + c[22] / (4096.0 - c[22]))')} AS bound FROM ({LINE_COUNTS})")
def ml_error_bound(spark, d):
    """Relative error of the likelihood estimate if its helper is wrong by one percent."""
    return by_group(spark, d).select(*GRP, significant(E.h_error_bound(F.lit(0.01), F.col("counts"), 12, 20)).alias("bound"))


_LL = f"-lam / 4096.0 * {_A} + list_sum(list_transform(range(1, 22), lambda k: CASE WHEN c[k + 1] > 0 THEN c[k + 1] * ln(1 - exp(-lam / 4096.0 * pow(2.0, -least(k, 20)))) ELSE 0.0 END))"


@query("loglik_curve", f"SELECT l_returnflag, l_linestatus, lam, {O.sig('ll')} AS ll FROM (SELECT l_returnflag, l_linestatus, lam, {_LL} AS ll FROM ({LINE_COUNTS}), (SELECT (i * 1000)::DOUBLE AS lam FROM range(1, 21) t(i)))")
def loglik_curve(spark, d):
    """The log-likelihood over a grid of rates."""
    grid = by_group(spark, d).withColumn("i", F.explode(F.sequence(F.lit(1), F.lit(20)))).withColumn("lam", F.col("i") * F.lit(1000.0))
    return grid.select(*GRP, "lam", significant(E.loglik(F.col("counts"), F.col("lam"), 12, 20)).alias("ll"))


@query("ideal_counts", f"SELECT l_returnflag, l_linestatus, {O.sig('c[1]::DOUBLE')} AS below, {O.sig('c[22]::DOUBLE')} AS above FROM ({LINE_COUNTS})")
def ideal_counts(spark, d):
    """Counts beyond the value range that the corrections stand for; they add up to the pooled ones."""
    k = by_group(spark, d).select(*GRP, F.explode(E.ideal_counts(F.col("counts"), 12, 20, 60)).alias("x"))
    return k.groupBy(*GRP).agg(F.sum(F.when(F.col("x.k") <= 0, F.col("x.c")).otherwise(0.0)).alias("b"), F.sum(F.when(F.col("x.k") > 20, F.col("x.c")).otherwise(0.0)).alias("a")).select(*GRP, significant(F.col("b")).alias("below"), significant(F.col("a")).alias("above"))


_SAT = O.counts(O.registers(LINE, [], 8, 6), [], 8, 6)


def _methods_sql(exprs: dict[str, str], source: str) -> str:
    return " UNION ALL ".join(f"SELECT '{m}' AS method, {O.sig('estimate')} AS estimate FROM (SELECT {e} AS estimate FROM ({source}))" for m, e in exprs.items())


@query("saturation_case", f"WITH RECURSIVE {O.ml_table('ml', _SAT, [], 8, 6)} {_methods_sql({'raw': O.raw(8, 6), 'corrected_raw': O.corrected(8, 6)}, _SAT)} UNION ALL SELECT 'ml', {O.sig('estimate')} FROM ml")
def saturation_case(spark, d):
    """Registers of few values, many of them saturated: the raw mean falls short, the others do not."""
    c = vectors(lineitem(spark, d), "l_orderkey", SketchSpec(8, 6, "md5_64"), [])
    col = F.col("counts")
    rows = F.array(*(F.struct(F.lit(n).alias("method"), significant(e).alias("estimate")) for n, e in (("raw", E.raw(col, 8, 6)), ("corrected_raw", E.corrected_raw(col, 8, 6)), ("ml", E.ml(col, 8, 6, 1e-12)))))
    return c.select(F.explode(rows).alias("r")).select("r.*")


_SMALL = {"events": ("events", "user_id"), "supplier": ("supplier", "s_suppkey"), "region": ("region", "r_regionkey")}
_SMALL_SRC = " UNION ALL ".join(f"SELECT '{n}' AS tbl, CAST({c} AS BIGINT) AS x FROM {t}" for n, (t, c) in _SMALL.items())
_SMALL_COUNTS = O.counts(O.registers(_SMALL_SRC, ["tbl"]), ["tbl"])


@query("small_range_case", f"WITH RECURSIVE {O.ml_table('ml', _SMALL_COUNTS, ['tbl'], 12, 20)} " + " UNION ALL ".join(f"SELECT tbl, '{m}' AS method, {O.sig('estimate')} AS estimate FROM (SELECT tbl, {e} AS estimate FROM ({_SMALL_COUNTS}))" for m, e in (("raw", O.raw(12, 20)), ("linear", O.linear(12)), ("corrected_raw", O.corrected(12, 20)))) + f" UNION ALL SELECT tbl, 'ml', {O.sig('estimate')} FROM ml")
def small_range_case(spark, d):
    """Few elements: the raw mean is far off, the others are near."""
    rows = None
    for name, (t, c) in _SMALL.items():
        own = table(spark, d, t).select(F.lit(name).alias("tbl"), F.col(c).cast("bigint").alias("x"))
        rows = own if rows is None else rows.unionByName(own)
    col = F.col("counts")
    methods = (("raw", E.raw(col, 12, 20)), ("linear", E.linear(col, 12)), ("corrected_raw", E.corrected_raw(col, 12, 20)), ("ml", E.ml(col, 12, 20, 1e-12)))
    found = F.array(*(F.struct(F.lit(n).alias("method"), significant(e).alias("estimate")) for n, e in methods))
    return vectors(rows, "x", SPEC, ["tbl"]).select("tbl", F.explode(found).alias("r")).select("tbl", "r.*")


@query("monotonicity_check", "SELECT 'corrected_raw' AS method, 0::BIGINT AS n_decreases UNION ALL SELECT 'ml', 0::BIGINT")
def monotonicity_check(spark, d):
    """How often an estimate falls while elements are added: never."""
    from pyspark.sql import Window

    grid = [*(200 * k for k in range(1, 81)), *(32_000 * 2**k for k in range(20)), S.WHOLE]
    snaps = S.multiplicity(S.snapshots(lineitem(spark, d), "l_orderkey", "l_orderkey", grid, SPEC), SPEC, ["bucket"])
    col = F.col("counts")
    found = F.array(*(F.struct(F.lit(n).alias("method"), e.alias("estimate")) for n, e in (("corrected_raw", E.corrected_raw(col, 12, 20)), ("ml", E.ml(col, 12, 20, 1e-12)))))
    rows = snaps.select("bucket", F.explode(found).alias("r")).select("bucket", "r.*")
    before = F.lag("estimate").over(Window.partitionBy("method").orderBy("bucket"))
    return rows.withColumn("fell", F.col("estimate") < before * (1 - 1e-9)).groupBy("method").agg(F.coalesce(F.sum(F.col("fell").cast("bigint")), F.lit(0)).alias("n_decreases"))
