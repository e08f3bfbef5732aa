"""Experiment workloads, and the surrounding operators over sketches."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import estimators as E
from ..functions.hashing import address, hash_word, rank
from ..functions.model import significant
from ..operators import joint as J
from ..operators import metrics, simulate
from ..operators import sketch as S
from ..sources.tables import pair_elements, table
from . import oracle as O
from .lineage import cut
from .queries_single import GRID, GRP, LINE, SPEC, lineitem, vectors
from .registry import query
from .spec import SketchSpec

SEEDS = 16
CONFIGS = ((12, 20), (8, 24), (16, 16), (22, 10), (12, 52), (12, 14))
BASE = SketchSpec(22, 42, "md5_64")


def seeded_counts(spark, d, shapes: tuple[tuple[int, int], ...], grid: list[int] = GRID) -> DataFrame:
    """(p, q, seed, bucket, k, c): value counts above 0 of growing key prefixes under independent hash functions, for all shapes at once.

    Every update is reduced to each shape; one aggregation then keeps for each register its value in every prefix, as
    the maximum over the buckets up to it, so that no sketch is built twice and none is cut again by window.
    """
    keys = lineitem(spark, d).select("l_orderkey").distinct().withColumn("bucket", S.grid_bucket(F.col("l_orderkey"), grid))
    each = keys.withColumn("seed", F.explode(F.sequence(F.lit(1), F.lit(SEEDS))))
    word = F.conv(F.substring(F.md5(F.concat(F.col("seed").cast("string"), F.lit(":"), F.col("l_orderkey").cast("string"))), 1, 16), 16, -10).cast("bigint")
    base = each.select("seed", "bucket", word.alias("h")).select("seed", "bucket", address(F.col("h"), BASE).alias("idx"), rank(F.col("h"), BASE).alias("reg"))
    own = []
    for p, q in shapes:
        idx, reg = S.reduced_register(F.col("idx"), F.col("reg"), BASE, p, q)
        own.append(F.struct(F.lit(p).alias("p"), F.lit(q).alias("q"), idx.alias("idx"), reg.alias("reg")))
    rows = base.select("seed", "bucket", F.explode(F.array(*own)).alias("x")).select("seed", "bucket", "x.*")
    upto = rows.groupBy("p", "q", "seed", "idx").agg(*(F.max(F.when(F.col("bucket") <= k, F.col("reg"))).alias(f"r{k}") for k in range(len(grid))))
    tall = upto.select("p", "q", "seed", F.posexplode(F.array(*(F.col(f"r{k}") for k in range(len(grid))))).alias("bucket", "k")).where("k IS NOT NULL")
    return tall.groupBy("p", "q", "seed", "bucket", F.col("k").cast("int").alias("k")).agg(F.count(F.lit(1)).alias("c"))


def truths(spark, d, grid: list[int] = GRID) -> DataFrame:
    """(bucket, n): exact distinct keys below each grid value; a few rows."""
    own = lineitem(spark, d).select("l_orderkey").distinct().groupBy(S.grid_bucket(F.col("l_orderkey"), grid).alias("bucket")).agg(F.count(F.lit(1)).alias("c")).where("bucket is not null")
    full = own.join(spark.range(len(grid)).select(F.col("id").cast("int").alias("bucket")), "bucket", "right")
    return full.select("bucket", F.sum(F.coalesce("c", F.lit(0))).over(Window.orderBy("bucket")).cast("double").alias("n"))  # len(grid) rows


def _vectors(counts: DataFrame, p: int, q: int) -> DataFrame:
    """R3 by seed and bucket of one shape of ``seeded_counts``."""
    return S.multiplicity_of_tall(counts.where((F.col("p") == p) & (F.col("q") == q)), SketchSpec(p, q, "md5_64"), ["seed", "bucket"])


def _curve(spark, d, specs, estimate) -> DataFrame:
    counts = cut(seeded_counts(spark, d, specs))  # SEEDS * buckets * (q + 1) rows for each shape
    out = None
    for p, q in specs:
        errors = _vectors(counts, p, q).join(F.broadcast(truths(spark, d)), "bucket").select(F.lit(p).alias("p"), F.lit(q).alias("q"), "bucket", metrics.relative_error(estimate(F.col("counts"), p, q), F.col("n")).alias("rel_err"))
        out = errors if out is None else out.unionByName(errors)
    return _rounded(metrics.summary(out, ["p", "q", "bucket"]), ["p", "q", "bucket"])


def _rounded(df: DataFrame, keys: list[str]) -> DataFrame:
    return df.select(*keys, *(F.round(c, 8).alias(c) for c in df.columns if c not in keys))


_PREFIXES = " UNION ALL ".join(f"SELECT {k} AS bucket, l_orderkey AS x FROM (SELECT DISTINCT l_orderkey FROM lineitem) WHERE l_orderkey < {t}" for k, t in enumerate(GRID))
_SEEDED = f"SELECT seed::INT AS seed, bucket, x FROM ({_PREFIXES}), range(1, {SEEDS + 1}) t(seed)"
_TRUTH = f"SELECT bucket, count(DISTINCT x)::DOUBLE AS n FROM ({_PREFIXES}) GROUP BY bucket"
_STATS = "round(avg(e), 8) AS bias, round(median(e), 8) AS median, round(stddev_pop(e), 8) AS stdev, round(sqrt(avg(e * e)), 8) AS rmse"


def _curve_sql(specs, expr) -> str:
    parts = [f"SELECT {p} AS p, {q} AS q, bucket, ({expr(p, q)}) / n - 1 AS e FROM ({O.counts(O.registers(_SEEDED, ['seed', 'bucket'], p, q, seed='seed'), ['seed', 'bucket'], p, q)}) JOIN ({_TRUTH}) USING (bucket)" for p, q in specs]
    return f"SELECT p, q, bucket, {_STATS} FROM ({' UNION ALL '.join(parts)}) GROUP BY p, q, bucket"


@query("curve_raw", _curve_sql(((12, 20),), O.raw))
def curve_raw(spark, d):
    """Error of the harmonic mean over growing sets: biased at both ends."""
    return _curve(spark, d, ((12, 20),), E.raw)


@query("curve_linear", _curve_sql(((12, 0),), lambda p, q: O.linear(p)))
def curve_linear(spark, d):
    """Error of linear counting from a bitmap."""
    return _curve(spark, d, ((12, 0),), lambda c, p, q: E.linear(c, p))


@query("curve_original", _curve_sql(((12, 20),), O.original))
def curve_original(spark, d):
    """Error of the composite, with its bump where it switches."""
    return _curve(spark, d, ((12, 20),), E.original)


@query("curve_corrected_raw", _curve_sql(CONFIGS, O.corrected))
def curve_corrected_raw(spark, d):
    """Error of the corrected mean for six shapes, all reduced from one fine sketch."""
    return _curve(spark, d, CONFIGS, E.corrected_raw)


def _ml_curve_sql(specs) -> str:
    ctes = [O.ml_table(f"ml{k}", O.counts(O.registers(_SEEDED, ["seed", "bucket"], p, q, seed="seed"), ["seed", "bucket"], p, q), ["seed", "bucket"], p, q, 70) for k, (p, q) in enumerate(specs)]
    parts = [f"SELECT {p} AS p, {q} AS q, bucket, estimate / n - 1 AS e FROM ml{k} JOIN ({_TRUTH}) USING (bucket)" for k, (p, q) in enumerate(specs)]
    return f"WITH RECURSIVE {', '.join(ctes)} SELECT p, q, bucket, {_STATS} FROM ({' UNION ALL '.join(parts)}) GROUP BY p, q, bucket"


@query("curve_ml", _ml_curve_sql(CONFIGS))
def curve_ml(spark, d):
    """Error of the likelihood estimate for the same six shapes."""
    return _curve(spark, d, CONFIGS, lambda c, p, q: E.ml(c, p, q, 1e-12))


_CMP = {"raw": lambda c: E.raw(c, 12, 20), "linear": lambda c: E.linear(c, 12), "original": lambda c: E.original(c, 12, 20), "corrected_raw": lambda c: E.corrected_raw(c, 12, 20)}
_CMP_SQL = {"raw": O.raw(12, 20), "linear": O.linear(12), "original": O.original(12, 20), "corrected_raw": O.corrected(12, 20)}
_CMP_COUNTS = O.counts(O.registers(_SEEDED, ["seed", "bucket"], seed="seed"), ["seed", "bucket"])


def _compared(spark, d, methods: dict) -> DataFrame:
    own = _vectors(seeded_counts(spark, d, ((12, 20),)), 12, 20)
    found = F.array(*(F.struct(F.lit(n).alias("method"), f(F.col("counts")).alias("estimate")) for n, f in methods.items()))
    rows = own.select("bucket", F.explode(found).alias("r")).select("bucket", "r.*").join(F.broadcast(truths(spark, d)), "bucket")
    stats = metrics.summary(rows.withColumn("rel_err", metrics.relative_error(F.col("estimate"), F.col("n"))), ["method", "bucket"])
    return _rounded(stats.select("method", "bucket", "stdev", "rmse"), ["method", "bucket"])


@query("stdev_comparison", f"SELECT method, bucket, round(stddev_pop(e), 8) AS stdev, round(sqrt(avg(e * e)), 8) AS rmse FROM ({' UNION ALL '.join(f'''SELECT '{m}' AS method, bucket, ({x}) / n - 1 AS e FROM ({_CMP_COUNTS}) JOIN ({_TRUTH}) USING (bucket)''' for m, x in _CMP_SQL.items())}) GROUP BY method, bucket")
def stdev_comparison(spark, d):
    """Spread of four estimators over growing sets."""
    return _compared(spark, d, _CMP)


@query("stdev_comparison_trained")
def stdev_comparison_trained(spark, d):
    """The same with the bias-corrected mean, whose table comes from simulation, and the likelihood at its usual tolerance."""
    from ..operators.baselines import bias_corrected

    return _compared(spark, d, _CMP | {"bias_corrected": lambda c: bias_corrected(c, 12, 20), "ml": lambda c: E.ml(c, 12, 20)})


#: Shape, and the parts into which every pair of sets is dealt: many small sketches, and larger ones of more registers.
JOINT_RUNS = (((12, 20), 400), ((20, 20), 60))


def joint_samples(spark, d, spec: SketchSpec, runs: int) -> DataFrame:
    """(config, run, target, truth, conventional, joint, iterations): both estimates of the sizes of every pair of sets in each part of its elements, beside the exact ones; parts share no element."""
    elements = pair_elements(spark, d).withColumn("run", F.pmod(F.xxhash64("x"), F.lit(runs)))
    by = ["pair", "run"]
    each = elements.groupBy(*by, "x").agg(F.bool_or(F.col("side") == 1).alias("l"), F.bool_or(F.col("side") == 2).alias("r"))
    n = lambda c: F.sum(c.cast("double"))
    exact = each.groupBy(*by).agg(n(F.col("l") & ~F.col("r")).alias("a"), n(F.col("r") & ~F.col("l")).alias("b"), n(F.col("l") & F.col("r")).alias("x"))
    stat = J.pair_statistic(S.build(elements, "x", spec, [*by, "side"]), spec, by)
    found = J.solve_bfgs(stat.select(*by, *(v.alias(k) for k, v in J.single_estimates(F.col("stat"), spec).items()), "stat").withColumnRenamed("union", "nu"), spec)
    one, two, nu = (F.col(c) for c in ("s1", "s2", "nu"))
    targets = {"only_left": (F.col("a"), nu - two, F.col("only_left")), "only_right": (F.col("b"), nu - one, F.col("only_right")), "both": (F.col("x"), one + two - nu, F.col("both")), "union": (F.col("a") + F.col("b") + F.col("x"), nu, F.col("only_left") + F.col("only_right") + F.col("both"))}
    rows = F.explode(F.array(*(F.struct(F.lit(t).alias("target"), truth.alias("truth"), own.alias("conventional"), joint.alias("joint")) for t, (truth, own, joint) in targets.items())))
    return found.join(exact, by).select(F.col("pair").alias("config"), "run", rows.alias("r"), F.col("iterations").cast("bigint").alias("iterations")).select("config", "run", "r.*", "iterations")


@query("joint_error_grid")
def joint_error_grid(spark, d):
    """Mean, standard deviation and root mean square error of joint and conventional estimates of the three sizes and of the union, and iterations, over the parts of every pair of sets."""
    parts = [simulate.joint_error_grid(joint_samples(spark, d, SketchSpec(p, q, seed=1), runs)).select(F.lit(p).alias("p"), F.lit(q).alias("q"), "*") for (p, q), runs in JOINT_RUNS]
    return parts[0].unionByName(parts[1])


#: Into how many parts the orders are dealt: each part is a sketch of its own, so there are as many errors.
PARTS = (8, 64, 512, 4096)
_METHODS = {"corrected_raw": lambda c, p, q: E.corrected_raw(c, p, q), "ml": lambda c, p, q: E.ml(c, p, q)}


def part_errors(spark, d, shapes: tuple[tuple[int, int], ...] = CONFIGS) -> DataFrame:
    """(p, q, parts, run, method, n, rel_err) of both estimators for the orders of each part, beside their exact number; all parts and shapes come from one aggregation."""
    keys = table(spark, d, "orders").where("o_orderkey IS NOT NULL").select("o_orderkey").distinct()
    own = F.pmod(F.xxhash64("o_orderkey"), F.lit(max(PARTS)))
    dealt = F.explode(F.array(*(F.struct(F.lit(k).alias("parts"), F.pmod(own, F.lit(k)).alias("run")) for k in PARTS)))  # each number divides the next, so parts are unions of smaller ones
    exact = keys.select(dealt.alias("x")).groupBy("x.parts", "x.run").agg(F.count(F.lit(1)).cast("double").alias("n"))
    word = keys.select(own.alias("own"), hash_word(F.col("o_orderkey"), BASE).alias("h"))
    base = word.select("own", address(F.col("h"), BASE).alias("idx"), rank(F.col("h"), BASE).alias("reg"))
    each = []
    for p, q in shapes:
        idx, reg = S.reduced_register(F.col("idx"), F.col("reg"), BASE, p, q)
        each += [F.struct(F.lit(p).alias("p"), F.lit(q).alias("q"), F.lit(k).alias("parts"), F.pmod(F.col("own"), F.lit(k)).alias("run"), idx.alias("idx"), reg.alias("reg")) for k in PARTS]
    registers = base.select(F.explode(F.array(*each)).alias("x")).select("x.*").groupBy("p", "q", "parts", "run", "idx").agg(F.max("reg").alias("reg"))
    tall = cut(registers.groupBy("p", "q", "parts", "run", F.col("reg").cast("int").alias("k")).agg(F.count(F.lit(1)).alias("c")))
    out = None
    for p, q in shapes:
        counts = S.multiplicity_of_tall(tall.where((F.col("p") == p) & (F.col("q") == q)), SketchSpec(p, q, "md5_64"), ["parts", "run"]).join(exact, ["parts", "run"])
        found = F.explode(F.array(*(F.struct(F.lit(m).alias("method"), f(F.col("counts"), p, q).alias("estimate")) for m, f in _METHODS.items()))).alias("r")
        rows = counts.select("parts", "run", "n", found).select(F.lit(p).alias("p"), F.lit(q).alias("q"), "parts", "run", "r.method", "n", metrics.relative_error(F.col("r.estimate"), F.col("n")).alias("rel_err"))
        out = rows if out is None else out.unionByName(rows)
    return out


@query("simulated_errors")
def simulated_errors(spark, d):
    """Bias, median, spread and bands of both estimators for six shapes, over the sketches of the orders' parts: from many small ones to few large ones."""
    errors, by = cut(part_errors(spark, d)), ["p", "q", "method", "parts"]
    sizes = errors.groupBy(*by).agg(F.count(F.lit(1)).alias("runs"), F.avg("n").alias("n"))
    return sizes.join(metrics.summary(errors, by), by).join(metrics.bands(errors, by), by)


#: Shapes whose ranges end at some 1e5 and 1e6 elements, and one that no table here fills; four sizes a decade, and the whole table.
RANGE_SHAPES = ((12, 2), (12, 6), (12, 20))
RANGE_GRID = [*(int(10 ** (k / 4)) for k in range(8, 30)), S.WHOLE]


@query("operating_range")
def operating_range(spark, d):
    """How far each of three shapes goes over growing prefixes of the orders before its mean error passes 3 %."""
    counts, by = cut(seeded_counts(spark, d, RANGE_SHAPES, RANGE_GRID)), ["p", "q", "method"]
    exact, errors = truths(spark, d, RANGE_GRID), None
    for p, q in RANGE_SHAPES:
        found = F.explode(F.array(*(F.struct(F.lit(m).alias("method"), f(F.col("counts"), p, q).alias("estimate")) for m, f in _METHODS.items()))).alias("r")
        rows = _vectors(counts, p, q).join(F.broadcast(exact), "bucket").select("n", found).select(F.lit(p).alias("p"), F.lit(q).alias("q"), "r.method", "n", metrics.relative_error(F.col("r.estimate"), F.col("n")).alias("rel_err"))
        errors = rows if errors is None else errors.unionByName(rows)
    return metrics.operating_range(cut(metrics.summary(errors, [*by, "n"])), by, 0.03)


# Groupings ------------------------------------------------------------------


def _estimated(r1: DataFrame, keys: list[str], spec: SketchSpec = SPEC) -> DataFrame:
    return S.multiplicity(r1, spec, keys).select(*keys, significant(E.corrected_raw(F.col("counts"), spec.p, spec.q)).alias("estimate"))


def _estimated_sql(source: str, keys: list[str], p: int = 12, q: int = 20) -> str:
    return f"SELECT {', '.join(keys)}, {O.sig('estimate')} AS estimate FROM (SELECT {', '.join(keys)}, {O.corrected(p, q)} AS estimate FROM ({O.counts(O.registers(source, keys, p, q), keys, p, q)}))"


def _sets(r1: DataFrame, sets: list[list[str]], keys: list[str]) -> DataFrame:
    """R1 by grouping sets of its keys and their level, from the sketches rather than from the facts."""
    level = sum((F.grouping(k).cast("int") * 2 ** (len(keys) - 1 - i) for i, k in enumerate(keys)), F.lit(0))
    return r1.groupingSets([[*s, "idx"] for s in sets], *keys, "idx").agg(F.max("reg").alias("reg"), level.cast("int").alias("level")).select(*keys, "level", "idx", "reg")


_GEO = "SELECT r_name, n_name, o_custkey AS x FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _geo(spark, d) -> DataFrame:
    nation, region = table(spark, d, "nation"), table(spark, d, "region")
    where = nation.join(region, F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
    return table(spark, d, "orders").select("o_custkey").join(table(spark, d, "customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).join(where, F.col("c_nationkey") == F.col("n_nationkey"))


@query("rollup_region_nation", _estimated_sql(f"SELECT r_name, n_name, 0 AS level, x FROM ({_GEO}) UNION ALL SELECT r_name, NULL, 1, x FROM ({_GEO}) UNION ALL SELECT NULL, NULL, 3, x FROM ({_GEO})", ["r_name", "n_name", "level"]))
def rollup_region_nation(spark, d):
    fine = S.build(_geo(spark, d), "o_custkey", SPEC, ["r_name", "n_name"])
    return _estimated(_sets(fine, [["r_name", "n_name"], ["r_name"], []], ["r_name", "n_name"]), ["r_name", "n_name", "level"])


@query("cube_flag_status", _estimated_sql(f"SELECT l_returnflag, l_linestatus, 0 AS level, x FROM ({LINE}) UNION ALL SELECT l_returnflag, NULL, 1, x FROM ({LINE}) UNION ALL SELECT NULL, l_linestatus, 2, x FROM ({LINE}) UNION ALL SELECT NULL, NULL, 3, x FROM ({LINE})", [*GRP, "level"]))
def cube_flag_status(spark, d):
    fine = S.build(lineitem(spark, d), "l_orderkey", SPEC, GRP)
    return _estimated(_sets(fine, [GRP, GRP[:1], GRP[1:], []], GRP), [*GRP, "level"])


@query("grouping_sets_orders", _estimated_sql("SELECT o_orderstatus, NULL AS o_orderpriority, 1 AS level, o_custkey AS x FROM orders UNION ALL SELECT NULL, o_orderpriority, 2, o_custkey FROM orders", ["o_orderstatus", "o_orderpriority", "level"]))
def grouping_sets_orders(spark, d):
    keys = ["o_orderstatus", "o_orderpriority"]
    return _estimated(_sets(S.build(table(spark, d, "orders"), "o_custkey", SPEC, keys), [keys[:1], keys[1:]], keys), [*keys, "level"])


@query("distinct_customers_by_region", f"SELECT r_name, exact, estimate FROM (SELECT r_name, count(DISTINCT x) AS exact FROM ({_GEO}) GROUP BY r_name) JOIN ({_estimated_sql(_GEO, ['r_name'])}) USING (r_name)")
def distinct_customers_by_region(spark, d):
    geo = _geo(spark, d)
    exact = geo.groupBy("r_name").agg(F.countDistinct("o_custkey").alias("exact"))
    return exact.join(_estimated(S.build(geo, "o_custkey", SPEC, ["r_name"]), ["r_name"]), "r_name")


# Windows, top-k, as-of and ranges ---------------------------------------------

DAY0 = "2024-01-01"
DAYS = 31
_DAY_SQL = f"date_diff('day', DATE '{DAY0}', CAST(ts AS DATE))::INT"


def _day() -> Column:
    return F.datediff(F.to_date("ts"), F.lit(DAY0).cast("date"))


def daily(spark, d) -> DataFrame:
    """R1 of the users of each day."""
    return S.build(table(spark, d, "events").withColumn("bucket", _day()), "user_id", SPEC, ["bucket"])


_RUNNING = f"SELECT d.bucket::INT AS bucket, user_id AS x FROM events JOIN range({DAYS}) d(bucket) ON {_DAY_SQL} <= d.bucket"


@query("running_distinct_daily", _estimated_sql(_RUNNING, ["bucket"]))
def running_distinct_daily(spark, d):
    """Users up to each day of the month."""
    return _estimated(S.running(daily(spark, d), DAYS), ["bucket"])


@query("rolling7_distinct_users", _estimated_sql(f"SELECT d.bucket::INT AS bucket, user_id AS x FROM events JOIN range({DAYS}) d(bucket) ON {_DAY_SQL} BETWEEN d.bucket - 6 AND d.bucket", ["bucket"]))
def rolling7_distinct_users(spark, d):
    """Users of the seven days up to each day: each day's registers go to the windows that hold it."""
    spread = daily(spark, d).withColumn("bucket", F.explode(F.sequence(F.col("bucket"), F.least(F.col("bucket") + 6, F.lit(DAYS - 1)))))
    return _estimated(S.rollup(spread, ["bucket"]), ["bucket"])


_BY_PRIORITY = _estimated_sql("SELECT o_orderpriority, o_custkey AS x FROM orders", ["o_orderpriority"])


@query("rank_keys_by_estimate", f"SELECT o_orderpriority, estimate, rank() OVER (ORDER BY estimate DESC, o_orderpriority)::INT AS rank, estimate - lag(estimate) OVER (ORDER BY estimate DESC, o_orderpriority) AS step FROM ({_BY_PRIORITY})")
def rank_keys_by_estimate(spark, d):
    """Order priorities by estimated customers; the ranked table has a row for each priority."""
    own = _estimated(S.build(table(spark, d, "orders"), "o_custkey", SPEC, ["o_orderpriority"]), ["o_orderpriority"])
    w = Window.orderBy(F.desc("estimate"), "o_orderpriority")
    return own.select("o_orderpriority", "estimate", F.rank().over(w).alias("rank"), (F.col("estimate") - F.lag("estimate").over(w)).alias("step"))


_PARTS = "SELECT l_partkey, o_custkey AS x FROM lineitem JOIN orders ON l_orderkey = o_orderkey"


@query("topk_parts_by_customers", f"SELECT l_partkey, estimate FROM ({_estimated_sql(_PARTS, ['l_partkey'], 8, 20)}) ORDER BY estimate DESC, l_partkey LIMIT 20")
def topk_parts_by_customers(spark, d):
    """The twenty parts with most customers."""
    spec = SketchSpec(8, 20, "md5_64")
    rows = lineitem(spark, d).select("l_orderkey", "l_partkey").join(table(spark, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    return _estimated(S.build(rows, "o_custkey", spec, ["l_partkey"]), ["l_partkey"], spec).orderBy(F.desc("estimate"), "l_partkey").limit(20)


@query("asof_snapshot", f"SELECT event_id, estimate FROM events LEFT JOIN ({_estimated_sql(_RUNNING, ['bucket'])}) s ON {_DAY_SQL} - 1 = s.bucket")
def asof_snapshot(spark, d):
    """For each event the estimate of the last snapshot before its day; snapshots are dense, so the as-of join is one on the day."""
    snaps = _estimated(S.running(daily(spark, d), DAYS), ["bucket"])
    return table(spark, d, "events").select("event_id", (_day() - 1).alias("bucket")).join(snaps, "bucket", "left").select("event_id", "estimate")  # Spark broadcasts the days if they are few


_RANGES = [(k, f"2024-01-{1 + 3 * k:02d} {(5 * k) % 24:02d}:30:00", f"2024-01-{3 + 3 * k + k % 3:02d} {(7 * k) % 24:02d}:00:00") for k in range(9)]


@query("events_in_ranges", _estimated_sql(f"SELECT r.range_id, props AS x FROM events JOIN (VALUES {', '.join(f'''({k}, TIMESTAMP '{a}', TIMESTAMP '{b}')''' for k, a, b in _RANGES)}) r(range_id, a, b) ON ts >= a AND ts < b", ["range_id"]))
def events_in_ranges(spark, d):
    """Distinct properties of the events in overlapping intervals: intervals are laid out by day, so the range join is one on the day and a filter."""
    ranges = spark.createDataFrame(_RANGES, "range_id int, a string, b string").select("range_id", F.col("a").cast("timestamp").alias("a"), F.col("b").cast("timestamp").alias("b"))
    days = ranges.withColumn("day", F.explode(F.sequence(F.to_date("a"), F.to_date("b"))))
    rows = table(spark, d, "events").withColumn("day", F.to_date("ts")).join(days, "day").where("ts >= a and ts < b")
    return _estimated(S.build(rows, "props", SPEC, ["range_id"]), ["range_id"])


# Strings, JSON, dates ---------------------------------------------------------


@query("distinct_hosts", _estimated_sql("SELECT regexp_extract(url, '^([a-z]+)://', 1) AS scheme, lower(regexp_extract(url, '^[a-z]+://([^/?#]+)', 1)) AS x FROM pages", ["scheme"]))
def distinct_hosts(spark, d):
    rows = table(spark, d, "pages").select(F.regexp_extract("url", "^([a-z]+)://", 1).alias("scheme"), F.lower(F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1)).alias("host"))
    return _estimated(S.build(rows, "host", SPEC, ["scheme"]), ["scheme"])


@query("distinct_json_k", _estimated_sql("SELECT event_type, json_extract_string(props, '$.k') AS x FROM events", ["event_type"]))
def distinct_json_k(spark, d):
    return _estimated(S.build(table(spark, d, "events").withColumn("k", F.get_json_object("props", "$.k")), "k", SPEC, ["event_type"]), ["event_type"])


@query("distinct_by_month", _estimated_sql("SELECT strftime(o_orderdate, '%Y-%m') AS month, o_custkey AS x FROM orders", ["month"]))
def distinct_by_month(spark, d):
    return _estimated(S.build(table(spark, d, "orders").withColumn("month", F.date_format("o_orderdate", "yyyy-MM")), "o_custkey", SPEC, ["month"]), ["month"])


@query("distinct_tokens_by_role", _estimated_sql("SELECT role, unnest(list_filter(string_split_regex(text, '[ \\t\\n\\r\\x0b\\f]+'), lambda w: w <> '')) AS x FROM conversations", ["role"]))
def distinct_tokens_by_role(spark, d):
    rows = table(spark, d, "conversations").select("role", F.explode(F.filter(F.split("text", "[ \\t\\n\\r\\x0b\\f]+"), lambda w: w != "")).alias("w"))
    return _estimated(S.build(rows, "w", SPEC, ["role"]), ["role"])


@query("distinct_vectors_by_label")
def distinct_vectors_by_label(spark, d):
    """Array-valued elements."""
    spec = SketchSpec()
    return S.multiplicity(S.build(table(spark, d, "embeddings"), "embedding", spec, ["label"]), spec, ["label"]).select("label", E.ml(F.col("counts"), 12, 20).alias("estimate"))


@query("labelled_documents", _estimated_sql("SELECT source, text AS x FROM documents SEMI JOIN (SELECT doc_id FROM labels WHERE quality = 1) USING (doc_id)", ["source"]))
def labelled_documents(spark, d):
    """Distinct texts of good documents by source: a semi join before the sketch."""
    good = table(spark, d, "labels").where("quality = 1").select("doc_id")
    return _estimated(S.build(table(spark, d, "documents").join(good, "doc_id", "left_semi"), "text", SPEC, ["source"]), ["source"])


# Batch twins of streams ---------------------------------------------------------


@query("events_tumbling", _estimated_sql("SELECT date_trunc('day', ts) AS window_start, user_id AS x FROM events", ["window_start"]))
def events_tumbling(spark, d):
    rows = table(spark, d, "events").withColumn("window_start", F.window("ts", "1 day")["start"])
    return _estimated(S.build(rows, "user_id", SPEC, ["window_start"]), ["window_start"])


@query("events_sliding", _estimated_sql("SELECT date_trunc('day', ts) - k * INTERVAL 1 DAY AS window_start, user_id AS x FROM events, range(2) t(k)", ["window_start"]))
def events_sliding(spark, d):
    rows = table(spark, d, "events").withColumn("window_start", F.window("ts", "2 days", "1 day")["start"])
    return _estimated(S.build(rows, "user_id", SPEC, ["window_start"]), ["window_start"])


_SESSION = "SELECT user_id, sum(CASE WHEN gap IS NULL OR gap >= INTERVAL 6 HOUR THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING)::INT AS session, props AS x FROM (SELECT *, ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS gap FROM events)"


@query("events_session", _estimated_sql(_SESSION, ["user_id", "session"], 8, 20))
def events_session(spark, d):
    """Distinct properties of each user's sessions; a session ends with a pause of six hours."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    gap = F.col("ts") - F.lag("ts").over(w)
    rows = table(spark, d, "events").withColumn("gap", gap).withColumn("session", F.sum(F.when(F.col("gap").isNull() | (F.col("gap") >= F.expr("INTERVAL 6 HOURS")), 1).otherwise(0)).over(w).cast("int"))
    spec = SketchSpec(8, 20, "md5_64")
    return _estimated(S.build(rows, "props", spec, ["user_id", "session"]), ["user_id", "session"], spec)


_SQL_ML = O.ml_table("ml", O.counts(O.registers(LINE, GRP), GRP), GRP, 12, 20)


@query("sql_surface", f"WITH RECURSIVE {_SQL_ML} SELECT l_returnflag, l_linestatus, {O.sig('c.estimate')} AS estimate, {O.sig('ml.estimate')} AS ml FROM (SELECT l_returnflag, l_linestatus, {O.corrected(12, 20)} AS estimate FROM ({O.counts(O.registers(LINE, GRP), GRP)})) c JOIN ml USING (l_returnflag, l_linestatus)")
def sql_surface(spark, d):
    """The whole way in SQL text with the registered functions."""
    from .. import sql

    sql.register(spark)
    lineitem(spark, d).createOrReplaceTempView("rs_lineitem")
    return spark.sql("""
        WITH updates AS (SELECT l_returnflag, l_linestatus, rs_hash(CAST(l_orderkey AS STRING)) AS h FROM rs_lineitem WHERE l_orderkey IS NOT NULL),
        registers AS (SELECT l_returnflag, l_linestatus, rs_address(h, 12) AS idx, MAX(rs_rank(h, 12, 20)) AS reg FROM updates GROUP BY ALL),
        seen AS (SELECT l_returnflag, l_linestatus, CAST(reg AS INT) AS k, COUNT(*) AS c FROM registers GROUP BY ALL),
        vectors AS (SELECT l_returnflag, l_linestatus, rs_counts(map_from_entries(collect_list(struct(k, c))), 12, 20) AS counts FROM seen GROUP BY ALL)
        SELECT l_returnflag, l_linestatus, rs_sig6(rs_estimate(counts)) AS estimate, rs_sig6(rs_ml(counts, 1e-12)) AS ml FROM vectors""")
