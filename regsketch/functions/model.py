"""Distribution of register values, and the special functions of the estimators, as columns."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

ALPHA = 1 / (2 * math.log(2))
INFINITY = float("inf")


def register_pmf(k: Column, nu: Column, q: int) -> Column:
    """Probability of value k in a register hit nu times."""
    upto = lambda j: F.pow(1 - F.pow(F.lit(2.0), -j), nu.cast("double"))
    return (
        F.when((k < 0) | (k > q + 1), 0.0)
        .when(nu == 0, F.when(k == 0, 1.0).otherwise(0.0))
        .when(k == 0, 0.0)
        .when(k <= q, upto(k) - F.when(k == 1, 0.0).otherwise(upto(k - 1)))
        .otherwise(1.0 - (upto(F.lit(q)) if q else F.lit(0.0)))
    )


def register_cdf(k: Column, rate: Column, m: int, q: int) -> Column:
    """Probability of a value up to k if elements come at this Poisson rate."""
    return F.when(k < 0, 0.0).when(k > q, 1.0).otherwise(F.exp(-rate / (F.lit(float(m)) * F.pow(F.lit(2.0), k.cast("double")))))


def poisson_pmf(k: Column, rate: Column, m: int, q: int) -> Column:
    return register_cdf(k, rate, m, q) - register_cdf(k - 1, rate, m, q)


def ripple(x: Column, reach: int = 60) -> Column:
    """The periodic factor ln 2 * sum over all k of 2**(k+x) exp(-2**(k+x)), which hardly differs from 1."""
    terms = F.sequence(F.lit(-reach), F.lit(reach))
    y = lambda k: F.pow(F.lit(2.0), k + (x - F.floor(x)))
    return math.log(2) * F.aggregate(terms, F.lit(0.0), lambda s, k: s + F.when(y(k) > 700, 0.0).otherwise(y(k) * F.exp(-y(k))))


def low_fill(x: Column, rounds: int = 40) -> Column:
    """x + sum of x**(2**k) 2**(k-1), unrolled; infinite at 1. For the empty registers' share."""
    total, power = x, x
    for k in range(1, rounds + 1):
        power = power * power
        total = total + power * float(2 ** (k - 1))
    return F.when(x >= 1, F.lit(INFINITY)).otherwise(total)


def low_fill_folded(x: Column, rounds: int) -> Column:
    """The same as a fold, which keeps plans small."""
    state = lambda z, p, w: F.struct(z.alias("z"), p.alias("p"), w.alias("w"))
    out = F.aggregate(F.sequence(F.lit(1), F.lit(rounds)), state(x, x, F.lit(1.0)), lambda s, _: state(s["z"] + s["p"] * s["p"] * s["w"], s["p"] * s["p"], s["w"] * 2), lambda s: s["z"])
    return F.when(x >= 1, F.lit(INFINITY)).otherwise(out)


def high_fill_folded(x: Column, rounds: int = 24) -> Column:
    """(1 - x - sum of (1 - x**(2**-k))**2 2**-k) / 3, zero at 0 and 1; for the registers below saturation."""
    state = lambda z, r, w: F.struct(z.alias("z"), r.alias("r"), w.alias("w"))
    step = lambda s, _: state(s["z"] - (1 - F.sqrt(s["r"])) * (1 - F.sqrt(s["r"])) * s["w"] / 2, F.sqrt(s["r"]), s["w"] / 2)
    out = F.aggregate(F.sequence(F.lit(1), F.lit(rounds)), state(1 - x, x, F.lit(1.0)), step, lambda s: s["z"] / 3)
    return F.when((x <= 0) | (x >= 1), 0.0).otherwise(out)


def high_fill_slow(x: Column, rounds: int = 60) -> Column:
    """(-x + sum of x**(2**-k) 2**-k) / 2: the same by definition, slowly converging."""
    out = F.aggregate(F.sequence(F.lit(1), F.lit(rounds)), -x, lambda s, k: s + F.pow(x, F.pow(F.lit(2.0), -k)) * F.pow(F.lit(2.0), -k))
    return F.when((x <= 0) | (x >= 1), 0.0).otherwise(out / 2)


def high_fill_by_log(x: Column, rounds: int = 40) -> Column:
    """By way of low_fill: both add up to alpha / ln(1/x) but for the ripple; loses digits near 1."""
    return F.when((x <= 0) | (x >= 1), 0.0).otherwise(ALPHA / -F.log(x) - low_fill_folded(x, rounds))


def h_exact(x: Column) -> Column:
    """1 - x / (e**x - 1), by a series near 0."""
    return F.when(x < 1e-5, x / 2 - x * x / 12).when(x > 700, 1.0).otherwise(1 - x / F.expm1(F.greatest(x, F.lit(1e-6))))


def h_series(x: Column) -> Column:
    """Up to the sixth power, for x up to one half."""
    y = x * x
    return x / 2 - y / 12 * (1 - y / 60 + y * y / 2520)


def h_doubled(x: Column, h: Column) -> Column:
    """h(2x) from h(x)."""
    rest, half = 1 - h, x / 2
    return (half + h * rest) / (half + rest)


def h_ladder(x: Column, rounds: int = 12) -> Column:
    """From the series at x / 2**rounds by doubling."""
    start = x / float(2**rounds)
    state = lambda y, h: F.struct(y.alias("y"), h.alias("h"))
    return F.aggregate(F.sequence(F.lit(1), F.lit(rounds)), state(start, h_series(start)), lambda s, _: state(s["y"] * 2, h_doubled(s["y"], s["h"])), lambda s: s["h"])


def significant(x: Column) -> Column:
    """Six significant digits, as both engines round them."""
    odd = x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(INFINITY))
    return F.when(odd, x).otherwise(F.format_string("%.5e", x).cast("double"))
