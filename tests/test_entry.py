"""The driver's contract: every query with SQL gives the same rows in DuckDB."""

import duckdb
import pytest

import __spark_entry__ as entry
from regsketch.plans import catalog

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SLOW = {"curve_ml", "union_joint_vs_merge", "jaccard_joint"}


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    c.execute("SET TimeZone = 'UTC'")
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return c


def normal(frame):
    def one(v):
        if v is None or v != v:
            return None
        return float(f"{v:.9g}") if isinstance(v, float) else str(v) if not hasattr(v, "__float__") else float(v)

    return sorted((tuple(one(v) for v in r) for r in frame[sorted(frame.columns)].astype(object).itertuples(index=False)), key=repr)


@pytest.mark.parametrize("name", sorted(set(catalog.oracle_sql()) - SLOW))
def test_query_is_its_sql(spark, sf, duck, name):
    got = catalog.queries()[name](spark, sf).toPandas()
    want = duck.execute(catalog.oracle_sql()[name]).fetch_df()
    assert sorted(got.columns) == sorted(want.columns)
    assert normal(got) == normal(want)


def test_joint_sizes_of_millions_are_those_of_the_sql(spark, duck):
    """Nine million elements that are nearly all shared: the likelihood is too flat for a search by its value to find three decimals."""
    from regsketch.plans import oracle as O
    from regsketch.plans import queries_pairs as P

    at = lambda first, *cells: [0] * first + [*cells] + [0] * (22 - first - len(cells))
    cells = {"lt1": at(0), "gt1": at(10, 4, 12, 20, 10, 10, 2, 1, 4), "lt2": at(9, 6, 19, 24, 10, 2, 2), "gt2": at(0), "eq": at(8, 3, 49, 393, 913, 1031, 718, 423, 231, 134, 80, 31, 12, 7, 8)}
    stat = spark.createDataFrame([("p", tuple(cells.values()))], "pair string, stat struct<" + ", ".join(f"{k}: array<bigint>" for k in cells) + ">")
    got = P._joint(stat).first()
    lists = "SELECT 'p' AS pair, " + ", ".join(f"{v}::BIGINT[] AS {k}" for k, v in cells.items())
    start = "SELECT l.*, greatest(1.0, nu - n2)::DOUBLE AS a, greatest(1.0, nu - n1)::DOUBLE AS b, greatest(1.0, n1 + n2 - nu)::DOUBLE AS x FROM s_l l JOIN s USING (pair)"
    want = duck.execute(f"WITH RECURSIVE {P.singles_sql('s', lists)}, {O.fixed_point('j', start, ['pair'], 12, 20, 2000)} SELECT a, b, x FROM j").fetchone()
    assert want[2] > 8e6 and [round(got[c], 3) for c in P.SIZES] == [round(v, 3) for v in want]


#: Queries that once made up their arguments.
ON_TABLES = ("h_function", "fill_functions", "fill_identity", "ripple_curve", "register_pmf", "pair_pmf", "equal_register_bounds", "equal_register_interval", "storage_factor")


@pytest.mark.parametrize("name", ON_TABLES)
def test_query_reads_a_table(spark, sf, name):
    assert catalog.queries()[name](spark, sf).inputFiles()


def test_entry_runs(spark):
    out = entry.entry(spark)
    rows = out.collect()
    assert len(rows) == 6 and all(abs(r["corrected_raw"] / r["exact"] - 1) < 0.1 for r in rows)


def test_names():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_queries_without_packages_of_the_text_operators(monkeypatch):
    """Where a package that only the text operators need is absent, the other queries are all there."""
    real = entry.importlib.import_module

    def absent(name):
        if name.startswith(("regsketch.llm", "corpus_pipeline")):
            raise ModuleNotFoundError("No module named 'xxhash'", name="xxhash")
        return real(name)

    monkeypatch.setattr(entry.importlib, "import_module", absent)
    assert entry.queries().keys() == catalog.queries().keys() and entry.oracle_sql().keys() == catalog.oracle_sql().keys()

    def broken(name):
        raise ModuleNotFoundError("No module named 'regsketch.plans.gone'", name="regsketch.plans.gone")

    monkeypatch.setattr(entry.importlib, "import_module", broken)
    with pytest.raises(ModuleNotFoundError):
        entry.queries()
