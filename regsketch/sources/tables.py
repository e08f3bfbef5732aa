"""The given tables, and the pairs of sets that the two-sketch methods are tried on."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One table; filters and columns asked for later are pushed into the scan."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


@dataclass(frozen=True)
class Side:
    """Elements ``item`` of the rows of ``table`` that meet ``condition``."""

    pair: str
    side: int
    table: str
    item: str
    condition: str


def _year(column: str, year: int) -> str:
    return f"{column} >= TIMESTAMP '{year}-01-01 00:00:00' AND {column} < TIMESTAMP '{year + 1}-01-01 00:00:00'"


#: Pairs of sets with large, small, no and complete overlap.
SIDES = (
    Side("S1", 1, "lineitem", "l_orderkey", "l_returnflag = 'A'"),
    Side("S1", 2, "lineitem", "l_orderkey", "l_returnflag = 'R'"),
    Side("S2", 1, "orders", "o_custkey", _year("o_orderdate", 1996)),
    Side("S2", 2, "orders", "o_custkey", _year("o_orderdate", 1997)),
    Side("S3", 1, "lineitem", "l_partkey", _year("l_shipdate", 1996)),
    Side("S3", 2, "lineitem", "l_partkey", _year("l_shipdate", 1997)),
    Side("S4", 1, "orders", "o_orderkey", "TRUE"),
    Side("S4", 2, "lineitem", "l_orderkey", "TRUE"),
    Side("S5", 1, "lineitem", "l_orderkey", "l_quantity <= 2"),
    Side("S5", 2, "lineitem", "l_orderkey", "l_quantity >= 49"),
    Side("S6", 1, "orders", "o_orderkey", "o_orderstatus = 'F'"),
    Side("S6", 2, "orders", "o_orderkey", "o_orderstatus = 'O'"),
    Side("S7", 1, "lineitem", "l_orderkey", "l_orderkey < 8000"),
    Side("S7", 2, "lineitem", "l_orderkey", "l_orderkey >= 7900"),
    Side("S8", 1, "customer", "c_custkey", "TRUE"),
    Side("S8", 2, "orders", "o_custkey", "o_orderpriority = '1-URGENT'"),
)


def pair_elements(spark: SparkSession, sf_dir: str, pairs: tuple[str, ...] | None = None) -> DataFrame:
    """(pair, side, x): one scan of each table that the pairs need, whose rows go to the sides they belong to."""
    wanted = [s for s in SIDES if pairs is None or s.pair in pairs]
    parts = []
    for name in sorted({s.table for s in wanted}):
        hits = F.array(*(F.when(F.expr(s.condition), F.struct(F.lit(s.pair).alias("pair"), F.lit(s.side).alias("side"), F.col(s.item).cast("bigint").alias("x"))) for s in wanted if s.table == name))
        parts.append(table(spark, sf_dir, name).select(F.explode(F.filter(hits, lambda h: h.isNotNull())).alias("h")).select("h.*"))
    return reduce(lambda a, b: a.unionByName(b), parts)


def pair_elements_sql(pairs: tuple[str, ...] | None = None) -> str:
    return " UNION ALL ".join(f"SELECT '{s.pair}' AS pair, {s.side} AS side, CAST({s.item} AS BIGINT) AS x FROM {s.table} WHERE {s.condition}" for s in SIDES if pairs is None or s.pair in pairs)
