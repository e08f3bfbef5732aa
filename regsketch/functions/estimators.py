"""Cardinality estimates from a multiplicity vector.

``counts`` is an array column of q + 2 numbers: how many registers have each value from 0 to
q + 1. Sums over values are unrolled, so that they stay within generated code;
the iterations of the likelihood are folds in the JVM.
"""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from .model import ALPHA, INFINITY, h_exact, high_fill_by_log, high_fill_folded, low_fill_folded

#: The constants of legacy implementations, to four digits.
LEGACY_ALPHA = {16: 0.673, 32: 0.697, 64: 0.709}


def count(counts: Column, k: int) -> Column:
    return F.get(counts, F.lit(k)).cast("double")


def middle(counts: Column, q: int) -> Column:
    """Sum over values 1 to q of their counts times 2**-value."""
    return reduce(lambda s, k: s + count(counts, k) * 2.0**-k, range(1, q + 1), F.lit(0.0))


def alpha(m: int) -> float:
    """The exact bias correction for m registers, by quadrature."""
    u = (np.arange(200_000) + 0.5) / 200_000  # x = u / (1 - u) maps 0..1 to 0..infinity
    x = u / (1 - u)
    with np.errstate(over="ignore"):
        inner = np.log2((2 + x) / (1 + x)) ** m / (1 - u) ** 2
    return float(1 / (m * inner.mean()))


def legacy_alpha(m: int) -> float:
    """The four-digit table and formula."""
    return LEGACY_ALPHA.get(m, 0.7213 / (1 + 1.079 / m))


def raw(counts: Column, p: int, q: int, factor: float | None = None) -> Column:
    """Harmonic mean of the registers' powers of two."""
    m = 1 << p
    total = count(counts, 0) + middle(counts, q) + count(counts, q + 1) * 2.0 ** -(q + 1)
    return (ALPHA if factor is None else factor) * m * m / total


def linear(counts: Column, p: int) -> Column:
    """From the share of empty registers; null if there are none. The exact likelihood estimate if q = 0."""
    m, empty = 1 << p, count(counts, 0)
    return F.when(empty > 0, m * F.log(m / F.when(empty > 0, empty)))


def large_range(estimate: Column, bits: int = 32) -> Column:
    """Correction for collisions of short hashes; null where it is not defined."""
    full = 2.0**bits
    return F.when(estimate < full, -full * F.log(1 - F.when(estimate < full, estimate) / full))


def original(counts: Column, p: int, q: int, factor: float | None = None) -> Column:
    """The first composite: linear below 2.5 m where registers are empty, corrected for 32-bit collisions above 2**32 / 30."""
    if p + q != 32:
        raise ValueError("the large-range step assumes words of 32 bits: p + q must be 32")
    return _composite(counts, p, q, factor, True)


def original_64(counts: Column, p: int, q: int, factor: float | None = None) -> Column:
    """The same for long hashes, which need no correction at the upper end."""
    return _composite(counts, p, q, factor, False)


def _composite(counts: Column, p: int, q: int, factor: float | None, large: bool) -> Column:
    m = 1 << p
    rough = raw(counts, p, q, factor)
    small = (rough <= 2.5 * m) & (count(counts, 0) > 0)
    upper = F.when(rough > 2.0**32 / 30, large_range(rough)).otherwise(rough) if large else rough
    return F.when(small, linear(counts, p)).otherwise(upper)


def corrected_raw(counts: Column, p: int, q: int, *, approx_high: bool = False, skip_high: bool = False, skip_low: bool = False) -> Column:
    """The harmonic mean with both ends of the value range mended: what registers at 0 and q + 1 would have been without the limits is filled in."""
    m = float(1 << p)
    low = count(counts, 0) if skip_low else m * low_fill_folded(count(counts, 0) / m, p + 8)
    share = 1 - count(counts, q + 1) / m
    high = F.lit(0.0) if skip_high else m * (high_fill_by_log(share, p + 8) if approx_high else high_fill_folded(share)) * 2.0**-q
    return _ratio(ALPHA * m * m, low + middle(counts, q) + high)


def _ratio(top: float, bottom: Column) -> Column:
    return F.when(bottom == 0, INFINITY).when(bottom == F.lit(INFINITY), 0.0).otherwise(top / F.when(bottom != 0, bottom))


def fill_tables(p: int) -> tuple[Column, Column]:
    """Both fill functions, times m, for every possible count of registers: constant arrays of m + 1 numbers, which the optimizer computes once."""
    m = float(1 << p)
    counts = F.sequence(F.lit(0), F.lit(1 << p))
    low = F.transform(counts, lambda c: m * low_fill_folded(c / m, p + 8))
    high = F.transform(counts, lambda c: m * high_fill_folded(1 - c / m))
    return low, high


def corrected_raw_table(counts: Column, p: int, q: int) -> Column:
    """``corrected_raw`` with both functions looked up."""
    low, high = fill_tables(p)
    bottom = F.get(low, count(counts, 0).cast("int")) + middle(counts, q) + F.get(high, count(counts, q + 1).cast("int")) * 2.0**-q
    return _ratio(ALPHA * float(1 << (2 * p)), bottom)


def ideal_counts(counts: Column, p: int, q: int, reach: int = 20) -> Column:
    """Estimated counts without limits, as (k, c): what is pooled at 0 spreads to k <= 0 and what is pooled at q + 1 to k > q.

    Below, C(k) = m (s**(2**-k) - s**(2**(1-k))) with s the empty share; above, C(q + j) = m (t**(2**-j) - t**(2**(1-j)))
    with t the share below saturation. The sums are the pooled counts again, but for what lies beyond ``reach``.
    """
    m = float(1 << p)
    s, t = count(counts, 0) / m, 1 - count(counts, q + 1) / m
    two = lambda e: F.pow(F.lit(2.0), e)
    power = lambda x, e: F.when(x > 0, F.pow(F.when(x > 0, x).otherwise(F.lit(1.0)), e)).otherwise(F.lit(0.0))
    entry = lambda k, c: F.struct(k.cast("int").alias("k"), c.alias("c"))
    below = F.transform(F.sequence(F.lit(-reach), F.lit(0)), lambda k: entry(k, m * (power(s, two(-k)) - power(s, two(1 - k)))))
    inside = F.transform(F.sequence(F.lit(1), F.lit(max(1, q))), lambda k: entry(k, F.get(counts, k).cast("double")))
    above = F.transform(F.sequence(F.lit(1), F.lit(reach)), lambda j: entry(F.lit(q) + j, m * (power(t, two(-j)) - power(t, two(1 - j)))))
    return F.concat(below, inside, above) if q else F.concat(below, above)


def ends(counts: Column, p: int, q: int) -> dict[str, Column]:
    """The sums that the likelihood needs: s, a, b and the number of registers that are not empty."""
    s = middle(counts, q)
    return {"s": s, "a": count(counts, 0) + s, "b": s + count(counts, q + 1) * 2.0**-q, "full": float(1 << p) - count(counts, 0)}


def ml_bounds(counts: Column, p: int, q: int) -> dict[str, Column]:
    """Bounds of the likelihood estimate: lo_weak, lo_strong, hi_strong, hi_weak."""
    e, m = ends(counts, p, q), float(1 << p)
    a, b, full = e["a"], e["b"], e["full"]
    safe_a, safe_b = F.when(a > 0, a), F.when(b > 0, b)
    top = F.greatest(*(F.when(count(counts, k) > 0, F.lit(float(min(k, q)))).otherwise(F.lit(0.0)) for k in range(q + 2)))
    scale = F.pow(F.lit(2.0), top)
    return {"lo_weak": m * full / (a + b / 2), "lo_strong": F.coalesce(m * full / safe_b * F.log1p(b / safe_a), F.lit(0.0)), "hi_strong": m * scale * F.log1p(full / (scale * safe_a)), "hi_weak": m * full / safe_a}


def score_at(x: Column, counts: Column, q: int, a: Column, h=h_exact) -> Column:
    """The increasing function of x = rate / m whose value is the number of full registers at the estimate."""
    terms = [F.when(count(counts, k) > 0, count(counts, k) * h(x * 2.0 ** -min(k, q))).otherwise(0.0) for k in range(1, q + 2)]
    return reduce(lambda s, t: s + t, terms, x * a)


def loglik(counts: Column, rate: Column, p: int, q: int) -> Column:
    """Poisson log-likelihood of the vector."""
    x = rate / float(1 << p)
    a = count(counts, 0) + middle(counts, q)
    terms = [F.when(count(counts, k) > 0, count(counts, k) * F.log(-F.expm1(-x * 2.0 ** -min(k, q)))).otherwise(0.0) for k in range(1, q + 2)]
    return reduce(lambda s, t: s + t, terms, -x * a)


def ml_trace(counts: Column, p: int, q: int, epsilon: float = 1e-2, cap: int = 64, solver: str = "secant", h=h_exact) -> Column:
    """(estimate, rounds) of the maximum-likelihood estimate, by a root search that rises to it from below."""
    m = float(1 << p)
    given = F.struct(counts.alias("c"), *(v.alias(k) for k, v in ends(counts, p, q).items()))
    state = lambda x, d, g, n, done: F.struct(x.alias("x"), d.alias("d"), g.alias("g"), n.alias("n"), done.alias("done"))

    def search(e: Column) -> Column:
        a, b, full = e["a"], e["b"], e["full"]
        strong = (b > 1.5 * a) & (a > 0) & (b > 0)
        start = F.when(strong, full / F.when(b > 0, b) * F.log1p(b / F.when(a > 0, a))).otherwise(full / F.when(a + b / 2 > 0, a + b / 2))
        first = state(start, start, F.lit(0.0), F.lit(0), F.lit(False))

        def secant(s: Column, _: Column) -> Column:
            now = score_at(s["x"], e["c"], q, a, h)  # evaluated only while the search goes on

            def moved(v: Column) -> Column:
                rising = v["now"] > s["g"]
                move = F.when(rising & (full > v["now"]), s["d"] * (full - v["now"]) / F.when(rising, v["now"] - s["g"])).otherwise(0.0)
                return state(s["x"] + move, move, v["now"], s["n"] + 1, move <= s["x"] * (epsilon / math.sqrt(m)))

            return F.when(s["done"], s).otherwise(_let(F.struct(now.alias("now")), moved))

        def newton(s: Column, _: Column) -> Column:
            now = score_at(s["x"], e["c"], q, a, h)
            slope = score_slope(s["x"], e["c"], q, a)

            def moved(v: Column) -> Column:
                move = F.when(full > v["now"], (full - v["now"]) / v["slope"]).otherwise(0.0)
                return state(s["x"] + move, move, v["now"], s["n"] + 1, move <= s["x"] * (epsilon / math.sqrt(m)))

            return F.when(s["done"], s).otherwise(_let(F.struct(now.alias("now"), slope.alias("slope")), moved))

        step = {"secant": secant, "newton": newton}[solver]
        return F.aggregate(F.sequence(F.lit(1), F.lit(cap)), first, step, lambda s: F.struct((m * s["x"]).alias("estimate"), s["n"].alias("rounds")))

    plain = F.when(count(counts, q + 1) == m, F.struct(F.lit(INFINITY).alias("estimate"), F.lit(0).alias("rounds")))
    return plain.when(count(counts, 0) == m, F.struct(F.lit(0.0).alias("estimate"), F.lit(0).alias("rounds"))).otherwise(_let(given, search))


def score_slope(x: Column, counts: Column, q: int, a: Column) -> Column:
    """Derivative of ``score_at`` in x."""

    def slope(y: Column) -> Column:
        grown = F.expm1(F.greatest(y, F.lit(1e-4)))
        return F.when(y < 1e-4, 0.5 - y / 6).when(y > 300, 0.0).otherwise((y * (grown + 1) - grown) / (grown * grown))

    terms = [F.when(count(counts, k) > 0, count(counts, k) * slope(x * 2.0 ** -min(k, q)) * 2.0 ** -min(k, q)).otherwise(0.0) for k in range(1, q + 2)]
    return reduce(lambda s, t: s + t, terms, a)


def _let(value: Column, body) -> Column:
    """``body`` of ``value``, which is computed once."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def ml(counts: Column, p: int, q: int, epsilon: float = 1e-2, solver: str = "secant") -> Column:
    """Maximum-likelihood estimate: 0 if all registers are empty, infinite if all are saturated."""
    return ml_trace(counts, p, q, epsilon, solver=solver)["estimate"]


def h_error_bound(error: Column, counts: Column, p: int, q: int) -> Column:
    """Relative error of the estimate if h is wrong by this factor."""
    m, top = float(1 << p), count(counts, q + 1)
    return error / 2 * (1 + top / F.when(m > top, m - top))


def geometric(counts: Column, p: int, q: int) -> Column:
    """The first generation: the mean of the values as a power of two."""
    m = float(1 << p)
    mean = reduce(lambda s, k: s + count(counts, k) * float(k), range(1, q + 2), F.lit(0.0)) / m
    return 0.39701 * m * F.pow(F.lit(2.0), mean)


def truncated_geometric(counts: Column, p: int, q: int, keep: float = 0.7, factor: float = 1.0) -> Column:
    """The same over the smallest values only; ``factor`` comes from simulation."""
    kept = float(int(keep * (1 << p)))
    total, before = F.lit(0.0), F.lit(0.0)
    for k in range(q + 2):
        use = F.greatest(F.lit(0.0), F.least(count(counts, k), kept - before))
        total, before = total + use * float(k), before + count(counts, k)
    return factor * float(1 << p) * F.pow(F.lit(2.0), total / kept)


METHODS = {
    "raw": raw,
    "linear": lambda c, p, q: linear(c, p),
    "original": original,
    "original_64": original_64,
    "corrected_raw": corrected_raw,
    "corrected_raw_table": corrected_raw_table,
    "ml": ml,
    "geometric": geometric,
}


def estimate(method: str, counts: Column, p: int, q: int) -> Column:
    """An estimate by its method's name."""
    if method not in METHODS:
        raise ValueError(f"unknown method {method!r}; there are {', '.join(METHODS)}")
    return METHODS[method](counts, p, q)
