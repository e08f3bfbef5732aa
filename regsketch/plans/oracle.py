"""DuckDB text for the same computations, put together from parts."""

from __future__ import annotations

import math

ALPHA = f"{1 / (2 * math.log(2))!r}e0"


def word(item: str, seed: str | None = None) -> str:
    """First 16 hexadecimal digits of md5 as an unsigned number."""
    text = f"CAST({item} AS VARCHAR)"
    text = f"concat({seed}, ':', {text})" if seed else text
    return f"('0x' || substr(md5({text}), 1, 16))::UBIGINT"


def address(h: str, p: int) -> str:
    return f"({h} >> {64 - p})::INT" if p else "0::INT"


def rank(h: str, p: int, q: int) -> str:
    if not q:
        return "1::TINYINT"
    rest = f"(({h} >> {64 - p - q}) & {(1 << q) - 1}::UBIGINT)"
    return f"(CASE WHEN {rest} = 0 THEN {q + 1} ELSE {q + 1} - length(bin({rest})) END)::TINYINT"


def _list(keys: list[str], *more: str) -> str:
    return ", ".join([*keys, *more])


def updates(source: str, keys: list[str], p: int, q: int, item: str = "x", seed: str | None = None) -> str:
    inner = f"SELECT {_list(keys, f'{word(item, seed)} AS h')} FROM ({source}) WHERE {item} IS NOT NULL"
    return f"SELECT {_list(keys, address('h', p) + ' AS idx', rank('h', p, q) + ' AS rank')} FROM ({inner})"


def registers(source: str, keys: list[str], p: int = 12, q: int = 20, item: str = "x", seed: str | None = None) -> str:
    return f"SELECT {_list(keys, 'idx', 'max(rank)::TINYINT AS reg')} FROM ({updates(source, keys, p, q, item, seed)}) GROUP BY {_list(keys, 'idx')}"


def counts(regs: str, keys: list[str], p: int = 12, q: int = 20) -> str:
    """Multiplicity vectors as lists c."""
    cells = ", ".join(f"count(*) FILTER (WHERE reg = {k})" for k in range(1, q + 2))
    by = f" GROUP BY {_list(keys)}" if keys else ""
    return f"SELECT {_list(keys, f'[CAST({1 << p} - count(*) AS BIGINT), {cells}]::BIGINT[] AS c')} FROM ({regs}){by}"


def middle(q: int, c: str = "c") -> str:
    return f"coalesce(list_sum(list_transform(range(1, {q + 1}), lambda k: {c}[k + 1] * pow(2.0, -k))), 0.0)" if q else "0.0"


def raw(p: int, q: int, c: str = "c", factor: str = ALPHA) -> str:
    return f"({factor} * {float(1 << 2 * p)!r} / ({c}[1] + {middle(q, c)} + {c}[{q + 2}] * pow(2.0, -{q + 1})))"


def linear(p: int, c: str = "c") -> str:
    m = float(1 << p)
    return f"(CASE WHEN {c}[1] > 0 THEN {m!r} * ln({m!r} / {c}[1]) END)"


def large_range(x: str) -> str:
    return f"(CASE WHEN {x} < 4294967296.0 THEN -4294967296.0 * ln(1 - {x} / 4294967296.0) END)"


def original(p: int, q: int, c: str = "c", large: bool = True) -> str:
    r = raw(p, q, c)
    upper = f"CASE WHEN {r} > {2**32 / 30!r} THEN {large_range(r)} ELSE {r} END" if large else r
    return f"(CASE WHEN {r} <= {2.5 * (1 << p)!r} AND {c}[1] > 0 THEN {linear(p, c)} ELSE {upper} END)"


def low_fill(x: str, p: int = 12) -> str:
    return f"(CASE WHEN {x} >= 1 THEN 'Infinity'::DOUBLE ELSE {x} + list_sum(list_transform(range(1, {p + 9}), lambda k: pow({x}, pow(2.0, k)) * pow(2.0, k - 1))) END)"


def high_fill(x: str, rounds: int = 30) -> str:
    return f"(CASE WHEN {x} <= 0 OR {x} >= 1 THEN 0.0 ELSE (1 - {x} - list_sum(list_transform(range(1, {rounds + 1}), lambda k: pow(1 - pow({x}, pow(2.0, -k)), 2) * pow(2.0, -k)))) / 3 END)"


def corrected(p: int, q: int, c: str = "c") -> str:
    m = float(1 << p)
    bottom = f"({m!r} * {low_fill(f'({c}[1] / {m!r})', p)} + {middle(q, c)} + {m!r} * {high_fill(f'(1 - {c}[{q + 2}] / {m!r})')} * {2.0**-q!r})"
    return f"(CASE WHEN {c}[1] = {1 << p} THEN 0.0 WHEN {bottom} = 0 THEN 'Infinity'::DOUBLE ELSE {ALPHA} * {m * m!r} / {bottom} END)"


def geometric(p: int, q: int, c: str = "c") -> str:
    m = float(1 << p)
    return f"(0.39701 * {m!r} * pow(2.0, list_sum(list_transform(range(1, {q + 2}), lambda k: {c}[k + 1] * k)) / {m!r}))"


def h(y: str) -> str:
    return f"(CASE WHEN {y} < 1e-5 THEN {y} / 2 - {y} * {y} / 12 WHEN {y} > 700 THEN 1.0 ELSE 1 - {y} / (exp({y}) - 1) END)"


def score(x: str, p: int, q: int, c: str = "c") -> str:
    part = h(f"({x} * pow(2.0, -least(k, {q})))")
    return f"({x} * ({c}[1] + {middle(q, c)}) + list_sum(list_transform(range(1, {q + 2}), lambda k: {c}[k + 1] * {part})))"


def ml_table(name: str, source: str, keys: list[str], p: int, q: int, rounds: int = 100) -> str:
    """CTEs that end in ``name`` (keys, estimate): the root by bisection. ``source`` has keys and c; keys are unique."""
    m = float(1 << p)
    mid = "((lo + hi) / 2)"
    low = score(mid, p, q)
    return f"""{name}_0 AS (SELECT *, {m!r} - c[1] AS full_, c[1] + {middle(q)} AS a_, {middle(q)} + c[{q + 2}] * {2.0**-q!r} AS b_ FROM ({source})),
{name}_1 AS (SELECT {_list(keys, 'c', 'full_', '0 AS i', 'full_ / (a_ + b_ / 2) AS lo', f"CASE WHEN a_ > 0 THEN full_ / a_ ELSE {2.0 ** (q + 6)!r} END AS hi")} FROM {name}_0 WHERE c[1] < {1 << p} AND c[{q + 2}] < {1 << p}
UNION ALL SELECT {_list(keys, 'c', 'full_', 'i + 1', f'CASE WHEN {low} < full_ THEN {mid} ELSE lo END', f'CASE WHEN {low} < full_ THEN hi ELSE {mid} END')} FROM {name}_1 WHERE i < {rounds}),
{name} AS (SELECT {_list(keys, f'{m!r} * (lo + hi) / 2 AS estimate')} FROM {name}_1 WHERE i = {rounds}
UNION ALL SELECT {_list(keys, "CASE WHEN c[1] = " + str(1 << p) + " THEN 0.0 ELSE 'Infinity'::DOUBLE END")} FROM {name}_0 WHERE c[1] = {1 << p} OR c[{q + 2}] = {1 << p})"""


def sig(x: str) -> str:
    return f"(CASE WHEN {x} IS NULL OR isinf({x}) OR isnan({x}) THEN {x} ELSE printf('%.5e', {x})::DOUBLE END)"


def loglik(a: str, b: str, x: str, p: int, q: int) -> str:
    """Joint log-likelihood over the lists lt1, gt1, lt2, gt2, eq."""
    m = float(1 << p)
    w = f"(pow(2.0, -least(k, {q})) / {m!r})"
    y = {n: f"exp(-({r}) * {w})" for n, r in (("a", a), ("b", b), ("x", x))}
    z = {n: f"(1 - {v})" for n, v in y.items()}
    t = lambda c, v: f"CASE WHEN {c}[k + 1] > 0 THEN {c}[k + 1] * ln({v}) ELSE 0.0 END"
    logs = " + ".join((t("lt1", f"{z['x']} + {y['x']} * {z['a']}"), t("lt2", f"{z['x']} + {y['x']} * {z['b']}"), t("gt1", z["a"]), t("gt2", z["b"]), t("eq", f"{z['x']} + {y['x']} * {z['a']} * {z['b']}")))
    logs = logs.replace("CASE", "(CASE").replace("END", "END)")
    lin = f"((lt1[k + 1] + eq[k + 1] + gt1[k + 1]) * ({a}) + (lt2[k + 1] + eq[k + 1] + gt2[k + 1]) * ({b}) + (lt1[k + 1] + eq[k + 1] + lt2[k + 1]) * ({x})) * pow(2.0, -k) / {m!r}"
    return f"(list_sum(list_transform(range(1, {q + 2}), lambda k: {logs})) - list_sum(list_transform(range(0, {q + 1}), lambda k: {lin})))"


def fixed_point(name: str, source: str, keys: list[str], p: int, q: int, rounds: int = 600) -> str:
    """CTEs that end in ``name`` (keys, a, b, x): rates times positive over linear part of the gradient, again and again. ``source`` has keys, the five lists, and start values a, b, x."""
    m = float(1 << p)
    w = f"(pow(2.0, -least(k, {q})) / {m!r})"
    y = {n: f"exp(-{n} * {w})" for n in "abx"}
    z = {n: f"(1 - {v})" for n, v in y.items()}
    d1, d2 = f"({z['x']} + {y['x']} * {z['a']})", f"({z['x']} + {y['x']} * {z['b']})"
    de = f"({z['x']} + {y['x']} * {z['a']} * {z['b']})"
    part = lambda c, top, bottom: f"(CASE WHEN {c}[k + 1] > 0 THEN {c}[k + 1] * {top} / {bottom} ELSE 0.0 END)"
    total = lambda *ps: f"list_sum(list_transform(range(1, {q + 2}), lambda k: ({' + '.join(ps)}) * {w}))"
    up = {
        "a": total(part("lt1", f"{y['x']} * {y['a']}", d1), part("eq", f"{y['x']} * {y['a']} * {z['b']}", de), part("gt1", y["a"], z["a"])),
        "b": total(part("lt2", f"{y['x']} * {y['b']}", d2), part("eq", f"{y['x']} * {y['b']} * {z['a']}", de), part("gt2", y["b"], z["b"])),
        "x": total(part("lt1", f"{y['x']} * {y['a']}", d1), part("lt2", f"{y['x']} * {y['b']}", d2), part("eq", f"{y['x']} * ({y['a']} + {z['a']} * {y['b']})", de)),
    }
    line = lambda *cs: f"list_sum(list_transform(range(0, {q + 1}), lambda k: ({' + '.join(f'{c}[k + 1]' for c in cs)}) * pow(2.0, -k) / {m!r}))"
    lists = ["lt1", "gt1", "lt2", "gt2", "eq"]
    return f"""{name}_0 AS (SELECT {_list(keys, *lists, line('lt1', 'eq', 'gt1') + ' AS la', line('lt2', 'eq', 'gt2') + ' AS lb', line('lt1', 'eq', 'lt2') + ' AS lx', 'a', 'b', 'x', '0 AS i')} FROM ({source})
UNION ALL SELECT {_list(keys, *lists, 'la', 'lb', 'lx', f'a * {up["a"]} / la', f'b * {up["b"]} / lb', f'x * {up["x"]} / lx', 'i + 1')} FROM {name}_0 WHERE i < {rounds}),
{name} AS (SELECT {_list(keys, 'a', 'b', 'x')} FROM {name}_0 WHERE i = {rounds})"""


def pair_lists(regs: str, keys: list[str], p: int, q: int) -> str:
    """The five lists of each pair from registers with column side."""
    both = f"SELECT {_list(keys, 'idx', 'coalesce(max(reg) FILTER (WHERE side = 1), 0)::INT AS k1', 'coalesce(max(reg) FILTER (WHERE side = 2), 0)::INT AS k2')} FROM ({regs}) GROUP BY {_list(keys, 'idx')}"
    cell = lambda cond, v: f"[{', '.join(f'count(*) FILTER (WHERE {cond} AND {v} = {k})' for k in range(q + 2))}]::BIGINT[]"
    eq = ", ".join([f"CAST({1 << p} - count(*) AS BIGINT)", *(f"count(*) FILTER (WHERE k1 = k2 AND k1 = {k})" for k in range(1, q + 2))])
    lists = [f"{cell('k1 < k2', 'k1')} AS lt1", f"{cell('k1 > k2', 'k1')} AS gt1", f"{cell('k2 < k1', 'k2')} AS lt2", f"{cell('k2 > k1', 'k2')} AS gt2", f"[{eq}]::BIGINT[] AS eq"]
    return f"SELECT {_list(keys, *lists)} FROM ({both}) GROUP BY {_list(keys)}"


def added(*lists: str) -> str:
    """Lists added up by place."""
    inner = " + ".join(f"{x}[k]" for x in lists)
    return f"list_transform(range(1, len({lists[0]}) + 1), lambda k: {inner})"
