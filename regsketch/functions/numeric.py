"""The same formulas in numpy, for solvers in Arrow batches, simulation and tests."""

from __future__ import annotations

import math
from functools import lru_cache

import numpy as np

ALPHA = 1 / (2 * math.log(2))


def low_fill(x: float) -> tuple[float, int]:
    """Value and rounds until it no longer changes."""
    if x >= 1:
        return math.inf, 0
    total, power, weight, rounds = x, x, 1.0, 0
    while True:
        power *= power
        rounds += 1
        new = total + power * weight
        weight *= 2
        if new == total:
            return total, rounds
        total = new


def high_fill(x: float) -> tuple[float, int]:
    """Value and rounds until it no longer changes."""
    if x <= 0 or x >= 1:
        return 0.0, 0
    total, root, weight, rounds = 1 - x, x, 1.0, 0
    while True:
        root = math.sqrt(root)
        weight /= 2
        rounds += 1
        new = total - (1 - root) ** 2 * weight
        if new == total:
            return total / 3, rounds
        total = new


def h(x: np.ndarray) -> np.ndarray:
    x = np.asarray(x, dtype=float)
    with np.errstate(over="ignore", invalid="ignore", divide="ignore"):
        return np.where(x < 1e-5, x / 2 - x * x / 12, 1 - x / np.expm1(np.maximum(x, 1e-6)))


def corrected_raw(counts: np.ndarray) -> float:
    m, q = counts.sum(), len(counts) - 2
    low, high = low_fill(counts[0] / m)[0], high_fill(1 - counts[q + 1] / m)[0]
    bottom = m * low + (counts[1 : q + 1] * 2.0 ** -np.arange(1, q + 1)).sum() + m * high * 2.0**-q
    return math.inf if bottom == 0 else float(ALPHA * m * m / bottom)


def ml(counts: np.ndarray, epsilon: float = 1e-2) -> tuple[float, int]:
    """The maximum-likelihood estimate and the rounds of its secant search."""
    m, q = float(counts.sum()), len(counts) - 2
    if counts[q + 1] == m:
        return math.inf, 0
    if counts[0] == m:
        return 0.0, 0
    k = np.minimum(np.arange(1, q + 2), q)
    weight, own = 2.0 ** -k.astype(float), counts[1:].astype(float)
    s = float((own[:q] * weight[:q]).sum())
    a, b, full = counts[0] + s, s + counts[q + 1] * 2.0**-q, m - counts[0]
    x = full / b * math.log1p(b / a) if b > 1.5 * a > 0 else full / (a + b / 2)
    step, before, rounds = x, 0.0, 0
    while step > x * epsilon / math.sqrt(m):
        rounds += 1
        now = x * a + float((own * h(x * weight)).sum())
        if now <= before or now >= full:
            break
        step *= (full - now) / (now - before)
        x, before = x + step, now
    return m * x, rounds


def corrected_raw_many(counts: np.ndarray) -> np.ndarray:
    """``corrected_raw`` of each row, with both fill functions looked up by the counts of empty and of saturated registers."""
    m, q = int(counts[0].sum()), counts.shape[1] - 2
    low, high = _fill_tables(m)
    some = np.flatnonzero(counts.any(0))  # values that no row has add nothing
    some = some[(some > 0) & (some <= q)]
    bottom = low[counts[:, 0]] + np.einsum("ij,j->i", counts[:, some], 2.0 ** -some.astype(float)) + high[counts[:, q + 1]] * 2.0**-q
    with np.errstate(divide="ignore"):
        return ALPHA * m * m / bottom


@lru_cache(maxsize=16)
def _fill_tables(m: int) -> tuple[np.ndarray, np.ndarray]:
    x = np.arange(m + 1) / m
    low, power, weight = x.copy(), x.copy(), 1.0
    for _ in range(max(1, m.bit_length() - 1) + 8):
        power = power * power
        low += power * weight
        weight *= 2
    low[-1] = math.inf
    root, high, weight = 1 - x, x.copy(), 1.0
    for _ in range(30):
        root = np.sqrt(root)
        weight /= 2
        high -= (1 - root) ** 2 * weight
    high = high / 3
    high[[0, -1]] = 0.0
    return m * low, m * high


def ml_many(counts: np.ndarray, epsilon: float = 1e-2, cap: int = 64, rows: int = 1024) -> tuple[np.ndarray, np.ndarray]:
    """The maximum-likelihood estimate of each row and its rounds; so many rows' secant searches go side by side, as fit a processor's cache."""
    parts = [_ml_side_by_side(counts[i : i + rows], epsilon, cap) for i in range(0, len(counts), rows)]
    return tuple(np.concatenate(x) for x in zip(*parts, strict=True)) if parts else (np.zeros(0), np.zeros(0, dtype=np.int64))


def _ml_side_by_side(counts: np.ndarray, epsilon: float, cap: int) -> tuple[np.ndarray, np.ndarray]:
    n, m, q = len(counts), float(counts[0].sum()), counts.shape[1] - 2
    k = np.minimum(np.arange(1, q + 2), q)
    weight = 2.0 ** -k.astype(float)
    out, rounds = np.zeros(n), np.zeros(n, dtype=np.int64)
    out[counts[:, q + 1] == m] = math.inf
    live = np.flatnonzero((counts[:, 0] < m) & (counts[:, q + 1] < m))
    used = np.flatnonzero(counts[live][:, 1:].any(0)) if len(live) else np.empty(0, dtype=np.int64)  # values that no row has add nothing
    own, weight = counts[live][:, 1:][:, used].astype(float), weight[used]
    s = (own * weight)[:, used < q].sum(1)
    c0 = counts[live, 0].astype(float)
    a, full = c0 + s, m - c0
    b = s + counts[live, q + 1] * 2.0**-q
    with np.errstate(divide="ignore", invalid="ignore"):
        x = np.where((b > 1.5 * a) & (a > 0), full / b * np.log1p(b / a), full / (a + b / 2))
    step, before, open_ = x.copy(), np.zeros(len(live)), np.arange(len(live))
    for _ in range(cap):
        if not len(open_):
            break
        y = x[open_, None] * weight
        with np.errstate(over="ignore", invalid="ignore"):
            high = y > 1e-5
            h_ = y / 2 - y * y / 12
            h_[high] = 1 - y[high] / np.expm1(y[high])
            now = x[open_] * a[open_] + np.einsum("ij,ij->i", own[open_], h_)
        rounds[live[open_]] += 1
        rising = (now > before[open_]) & (now < full[open_])
        move = np.where(rising, step[open_] * (full[open_] - now) / np.where(rising, now - before[open_], 1), 0.0)
        x[open_] += move
        step[open_], before[open_] = move, now
        open_ = open_[move > x[open_] * epsilon / math.sqrt(m)]
    out[live] = m * x
    return out, rounds


def joint_terms_many(stats: np.ndarray, rates: np.ndarray, p: int, q: int) -> tuple[np.ndarray, np.ndarray]:
    """Log-likelihood of each pair and its gradient in the logs of the three rates; stats is (pairs, 5, q + 2): lt1, gt1, lt2, gt2, eq."""
    m = float(1 << p)
    w = 2.0 ** -np.minimum(np.arange(1, q + 2), q).astype(float) / m
    xa, xb, xx = (rates[:, k, None] * w for k in range(3))
    za, zb, zx = (-np.expm1(-v) for v in (xa, xb, xx))
    ya, yb, yx = 1 - za, 1 - zb, 1 - zx
    lt1, gt1, lt2, gt2, eq = (stats[:, c, 1:] for c in range(5))
    tiny = 1e-300
    d1, d2, de = np.maximum(zx + yx * za, tiny), np.maximum(zx + yx * zb, tiny), np.maximum(zx + yx * za * zb, tiny)
    ga, gb = np.maximum(za, tiny), np.maximum(zb, tiny)
    value = (lt1 * np.log(d1) + lt2 * np.log(d2) + gt1 * np.log(ga) + gt2 * np.log(gb) + eq * np.log(de)).sum(1)
    w0 = 2.0 ** -np.arange(q + 1).astype(float) / m
    a0, b0, c0, d0, e0 = (stats[:, c, : q + 1] for c in range(5))
    linear = np.stack([((a0 + e0 + b0) * w0).sum(1), ((c0 + e0 + d0) * w0).sum(1), ((a0 + e0 + c0) * w0).sum(1)], axis=1) * rates
    grad = np.stack([
        (lt1 * yx * xa * ya / d1 + eq * yx * xa * ya * zb / de + gt1 * xa * ya / ga).sum(1),
        (lt2 * yx * xb * yb / d2 + eq * yx * xb * yb * za / de + gt2 * xb * yb / gb).sum(1),
        (lt1 * xx * yx * ya / d1 + lt2 * xx * yx * yb / d2 + eq * xx * yx * (ya + za * yb) / de).sum(1),
    ], axis=1)
    return value - linear.sum(1), grad - linear


def joint_ml_many(stats: np.ndarray, p: int, q: int, tolerance: float | None = None, cap: int = 300) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For each pair the sizes (only first, only second, both), the iterations, and whether the sizes are determined, by BFGS in log rates, all pairs side by side.

    A pair's search stops when no log rate moves by more than ``tolerance`` (1e-2 / sqrt(m) by default). Sketches of
    which every register is empty on one side share nothing; where one sketch lies above the other throughout, what
    they share is not determined.
    """
    n, m = len(stats), float(1 << p)
    sizes, rounds = np.zeros((n, 3)), np.zeros(n, dtype=np.int64)
    if not n:
        return sizes, rounds, np.zeros(0, dtype=bool)
    lt1, gt1, lt2, gt2, eq = (stats[:, c] for c in range(5))
    one, two, union = lt1 + gt1 + eq, lt2 + gt2 + eq, gt1 + gt2 + eq
    n1, n2, nu = (ml_many(v.astype(np.int64), 1e-6)[0] for v in (one, two, union))
    known = (lt1.sum(1) + eq.sum(1) > 0) & (lt2.sum(1) + eq.sum(1) > 0)
    apart = (lt1 + lt2 + eq)[:, 1:].sum(1) == 0
    endless = ~apart & ~(np.isfinite(n1) & np.isfinite(n2))
    known &= ~endless
    equal = ~apart & ~endless & (lt1.sum(1) + gt1.sum(1) == 0)
    sizes[apart | endless, :2] = np.stack([n1, n2], axis=1)[apart | endless]
    sizes[endless, 2] = math.nan
    sizes[equal, 2] = nu[equal]
    live = np.flatnonzero(~(apart | endless | equal))
    if not len(live):
        return sizes, rounds, known
    own = stats[live].astype(float)
    stop, floor = 1e-2 / math.sqrt(m) if tolerance is None else tolerance, math.log(1e-9)
    phi = np.log(np.maximum(1.0, np.stack([nu - n2, nu - n1, n1 + n2 - nu], axis=1)[live]))
    value, grad = joint_terms_many(own, np.exp(phi), p, q)
    inverse = np.eye(3)[None] / np.maximum(1.0, np.abs(grad).max(1))[:, None, None]
    turn, open_ = np.zeros(len(live), dtype=np.int64), np.arange(len(live))
    for _ in range(cap):
        if not len(open_):
            break
        turn[open_] += 1
        was, now_value, now_grad = phi[open_], value[open_], grad[open_]
        move = np.einsum("nij,nj->ni", inverse[open_], now_grad)
        move *= np.minimum(1.0, 2.0 / np.maximum(1e-12, np.abs(move).max(1)))[:, None]
        gain = (now_grad * move).sum(1)
        scale = np.ones(len(open_))
        new, new_value, new_grad = was.copy(), now_value.copy(), now_grad.copy()
        seek = np.arange(len(open_))
        while len(seek):  # back to steps that do not lower the likelihood
            new[seek] = np.maximum(was[seek] + scale[seek, None] * move[seek], floor)
            new_value[seek], new_grad[seek] = joint_terms_many(own[open_[seek]], np.exp(new[seek]), p, q)
            enough = new_value[seek] >= now_value[seek] + 1e-4 * scale[seek] * gain[seek] - 1e-9 * np.abs(now_value[seek]) * (scale[seek] < 1e-3)
            seek = seek[~enough & (scale[seek] >= 1e-9)]
            scale[seek] /= 2
        s, y = new - was, now_grad - new_grad
        sy = (s * y).sum(1)
        rises = np.flatnonzero(sy > 1e-14)
        t = np.eye(3)[None] - s[rises, :, None] * y[rises, None, :] / sy[rises, None, None]
        inverse[open_[rises]] = t @ inverse[open_[rises]] @ t.transpose(0, 2, 1) + s[rises, :, None] * s[rises, None, :] / sy[rises, None, None]
        phi[open_], value[open_], grad[open_] = new, new_value, new_grad
        open_ = open_[np.abs(s).max(1) > stop]
    rates = np.exp(phi)
    without = rates.copy()
    without[:, 2] = 1e-9
    none = (rates[:, 2] < 0.5) & (joint_terms_many(own, without, p, q)[0] >= value - 1e-9 * np.abs(value))
    rates[none, 2] = 0.0
    rates[rates < 1e-6] = 0.0
    sizes[live], rounds[live] = rates, turn
    return sizes, rounds, known


def joint_rounds_many(stats: np.ndarray, p: int, q: int, rounds: int) -> np.ndarray:
    """For each pair the sizes (only first, only second, both) after so many rounds of the multiplicative fixed point: each rate times the positive over the linear part of its gradient.

    It begins with inclusion-exclusion, 1 at least, and keeps its digits where the likelihood is too flat for a search by its value.
    """
    n, m = len(stats), float(1 << p)
    lt1, gt1, lt2, gt2, eq = (stats[:, c] for c in range(5))
    n1, n2, nu = (ml_many(v.astype(np.int64), 1e-12)[0] for v in (lt1 + gt1 + eq, lt2 + gt2 + eq, gt1 + gt2 + eq))
    rates = np.maximum(1.0, np.stack([nu - n2, nu - n1, n1 + n2 - nu], axis=1)) if n else np.zeros((0, 3))
    w = 2.0 ** -np.minimum(np.arange(1, q + 2), q).astype(float) / m
    w0 = 2.0 ** -np.arange(q + 1).astype(float) / m
    first = [v[:, : q + 1].astype(float) for v in (lt1, gt1, lt2, gt2, eq)]
    linear = np.stack([((first[0] + first[4] + first[1]) * w0).sum(1), ((first[2] + first[4] + first[3]) * w0).sum(1), ((first[0] + first[4] + first[2]) * w0).sum(1)], axis=1)
    lt1, gt1, lt2, gt2, eq = (v[:, 1:].astype(float) for v in (lt1, gt1, lt2, gt2, eq))
    share = lambda c, top, bottom: np.divide(c * top, bottom, out=np.zeros_like(c), where=(c > 0) & (bottom > 0))
    for _ in range(rounds):
        za, zb, zx = (-np.expm1(-rates[:, k, None] * w) for k in range(3))
        ya, yb, yx = 1 - za, 1 - zb, 1 - zx
        d1, d2, de = zx + yx * za, zx + yx * zb, zx + yx * za * zb
        one, two = share(lt1, yx * ya, d1), share(lt2, yx * yb, d2)
        up = np.stack([
            ((one + share(eq, yx * ya * zb, de) + share(gt1, ya, za)) * w).sum(1),
            ((two + share(eq, yx * yb * za, de) + share(gt2, yb, zb)) * w).sum(1),
            ((one + two + share(eq, yx * (ya + za * yb), de)) * w).sum(1),
        ], axis=1)
        rates = np.divide(rates * up, linear, out=np.zeros_like(rates), where=linear > 0)
    return rates
