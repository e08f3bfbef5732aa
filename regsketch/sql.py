"""The methods as SQL functions.

``register`` adds functions with SQL bodies, which Catalyst inlines, and the Arrow-backed ones: rs_sketch (aggregate of rows into
packed registers), rs_merge (aggregate of packed registers) and the table function rs_registers.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .plans.ship import ship

_REST = "shiftrightunsigned(h, 64 - p - q) & (shiftleft(1L, q) - 1)"
_H = "CASE WHEN y < 1e-5 THEN y / 2 - y * y / 12 WHEN y > 700 THEN 1D ELSE 1 - y / expm1(greatest(y, 1e-6)) END"
_Q = "(size(counts) - 2)"
_M = "CAST(aggregate(counts, 0L, (a, c) -> a + c) AS DOUBLE)"
_MIDDLE = f"aggregate(slice(transform(counts, (c, k) -> c * pow(2D, -k)), 2, greatest({_Q}, 0)), 0D, (a, c) -> a + c)"



def _score(x: str) -> str:
    """The likelihood's score at x, written out: a lambda's variables cannot be given to another SQL function."""
    y = f"({x} * pow(2D, -least(k, {_Q})))"
    return f"({x} * (counts[0] + {_MIDDLE}) + aggregate(slice(transform(counts, (c, k) -> CASE WHEN c = 0 THEN 0D ELSE c * ({_H.replace('y', y)}) END), 2, {_Q} + 1), 0D, (a, c) -> a + c))"


FUNCTIONS = {
    "rs_hash(s STRING) RETURNS BIGINT": "CAST(conv(substr(md5(s), 1, 16), 16, -10) AS BIGINT)",
    "rs_address(h BIGINT, p INT) RETURNS INT": "CASE WHEN p = 0 THEN 0 ELSE CAST(shiftrightunsigned(h, 64 - p) AS INT) END",
    "rs_rank(h BIGINT, p INT, q INT) RETURNS TINYINT": f"CAST(CASE WHEN q = 0 THEN 1 WHEN ({_REST}) = 0 THEN q + 1 ELSE q + 1 - length(bin({_REST})) END AS TINYINT)",
    "rs_counts(seen MAP<INT, BIGINT>, p INT, q INT) RETURNS ARRAY<BIGINT>": "transform(sequence(0, q + 1), k -> CASE WHEN k = 0 THEN shiftleft(1L, p) - aggregate(map_values(seen), 0L, (a, c) -> a + c) ELSE coalesce(try_element_at(seen, k), 0L) END)",
    "rs_low_fill(x DOUBLE, rounds INT) RETURNS DOUBLE": "CASE WHEN x >= 1 THEN double('Infinity') ELSE x + aggregate(sequence(1, rounds), 0D, (a, k) -> a + pow(x, pow(2D, k)) * pow(2D, k - 1)) END",
    "rs_high_fill(x DOUBLE) RETURNS DOUBLE": "CASE WHEN x <= 0 OR x >= 1 THEN 0D ELSE (1 - x - aggregate(sequence(1, 30), 0D, (a, k) -> a + pow(1 - pow(x, pow(2D, -k)), 2) * pow(2D, -k))) / 3 END",
    "rs_estimate(counts ARRAY<BIGINT>) RETURNS DOUBLE": f"CASE WHEN counts[0] = {_M} THEN 0D WHEN counts[{_Q} + 1] = {_M} THEN double('Infinity') ELSE {1 / (2 * math.log(2))!r}D * {_M} * {_M} / ({_M} * rs_low_fill(counts[0] / {_M}, 30) + {_MIDDLE} + {_M} * rs_high_fill(1 - counts[{_Q} + 1] / {_M}) * pow(2D, -{_Q})) END",
    "rs_h(y DOUBLE) RETURNS DOUBLE": _H,
    "rs_score(x DOUBLE, counts ARRAY<BIGINT>) RETURNS DOUBLE": _score("x"),
    "rs_ml(counts ARRAY<BIGINT>, epsilon DOUBLE) RETURNS DOUBLE": f"""CASE WHEN counts[0] = {_M} THEN 0D WHEN counts[{_Q} + 1] = {_M} THEN double('Infinity') ELSE
        aggregate(sequence(1, 48), named_struct('x', ({_M} - counts[0]) / (counts[0] + {_MIDDLE} + ({_MIDDLE} + counts[{_Q} + 1] * pow(2D, -{_Q})) / 2), 'd', ({_M} - counts[0]) / (counts[0] + {_MIDDLE} + ({_MIDDLE} + counts[{_Q} + 1] * pow(2D, -{_Q})) / 2), 'g', 0D, 'done', false),
          (s, i) -> CASE WHEN s.done THEN s ELSE transform(array({_score('s.x')}), now -> transform(array(CASE WHEN now > s.g AND now < {_M} - counts[0] THEN s.d * ({_M} - counts[0] - now) / (now - s.g) ELSE 0D END), move -> named_struct('x', s.x + move, 'd', move, 'g', now, 'done', move <= s.x * epsilon / sqrt({_M})))[0])[0] END,
          s -> {_M} * s.x) END""",
    "rs_sig6(x DOUBLE) RETURNS DOUBLE": "CASE WHEN x IS NULL OR isnan(x) OR abs(x) = double('Infinity') THEN x ELSE CAST(format_string('%.5e', x) AS DOUBLE) END",
}


def register(spark: SparkSession) -> None:
    """Add all functions to the session."""
    for head, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    ship(spark)

    @F.pandas_udf(T.BinaryType())
    def rs_sketch(idx: pd.Series, rank: pd.Series, m: pd.Series) -> bytes:
        registers = np.zeros(int(m.iloc[0]) if len(m) else 0, dtype=np.uint8)
        np.maximum.at(registers, idx.to_numpy(), rank.to_numpy().astype(np.uint8))
        return registers.tobytes()

    @F.pandas_udf(T.BinaryType())
    def rs_merge(blobs: pd.Series) -> bytes:
        rows = [np.frombuffer(b, dtype=np.uint8) for b in blobs if b is not None]
        return np.maximum.reduce(rows).tobytes() if rows else b""

    class Registers:
        def eval(self, blob: bytes):
            registers = np.frombuffer(blob or b"", dtype=np.uint8)
            for i in np.flatnonzero(registers):
                yield int(i), int(registers[i])

    spark.udf.register("rs_sketch", rs_sketch)
    spark.udf.register("rs_merge", rs_merge)
    spark.udtf.register("rs_registers", F.udtf(Registers, returnType="idx: int, reg: int"))
