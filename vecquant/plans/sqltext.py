"""SQL text of the curves and of common subqueries, for checks against another engine."""

from __future__ import annotations


def num(v: float | str) -> str:
    """A number as a double."""
    return v if isinstance(v, str) else f"CAST({float(v)!r} AS DOUBLE)"


def raw(curve: str, x: str, a: float | str, x0: float | str) -> str:
    a, x0 = num(a), num(x0)
    if curve == "logi":
        return f"(1 / (1 + exp(-{a} * (({x}) - {x0}))))"
    if curve == "logi2":
        return f"(1 / (1 + pow(2.0, -{a} * (({x}) - {x0}))))"
    z = pwl_exp2(f"({a} * (({x}) - {x0}))")
    return f"({z} / ({z} + 1))"


def raw_inverse(curve: str, y: str, a: float | str, x0: float | str) -> str:
    a, x0, odds = num(a), num(x0), f"(({y}) / (1 - ({y})))"
    if curve == "logi":
        return f"(ln({odds}) / {a} + {x0})"
    if curve == "logi2":
        return f"(log2({odds}) / {a} + {x0})"
    return f"({pwl_log2(odds)} / {a} + {x0})"


def pwl_log2(z: str) -> str:
    p = f"(floor(log2({z})) + 1)"
    m = f"(({z}) / pow(2.0, {p}))"
    return f"(CASE WHEN {m} >= 1 THEN 2 * ({m} / 2 - 1) + {p} + 1 WHEN {m} < 0.5 THEN 2 * ({m} * 2 - 1) + {p} - 1 ELSE 2 * ({m} - 1) + {p} END)"


def pwl_exp2(v: str) -> str:
    p = f"floor(({v}) + 1)"
    return f"(((({v}) - {p}) / 2 + 1) * pow(2.0, {p}))"


def kuma(x: str, a: float | str, b: float | str) -> str:
    return f"(1 - pow(1 - pow({x}, {num(a)}), {num(b)}))"


def kuma_inverse(y: str, a: float | str, b: float | str) -> str:
    return f"pow(1 - pow(1 - ({y}), 1 / {num(b)}), 1 / {num(a)})"


def bend(curve: str, x: str = "value", lo: str = "lo", hi: str = "hi", p0: float | str = 1.0, p1: float | str = 1.0) -> str:
    width = f"({hi} - {lo})"
    if curve == "unif":
        bent = f"(({x} - {lo}) / {width})"
    elif curve == "kuma":
        bent = kuma(f"(({x} - {lo}) / {width})", p0, p1)
    else:
        low, high = raw(curve, f"{lo} / {width}", p0, p1), raw(curve, f"{hi} / {width}", p0, p1)
        bent = f"(({raw(curve, f'{x} / {width}', p0, p1)} - {low}) / ({high} - {low}))"
    return f"(CASE WHEN {width} > 0 THEN {bent} ELSE 0.0 END)"


def unbend(curve: str, y: str, lo: str = "lo", hi: str = "hi", p0: float | str = 1.0, p1: float | str = 1.0) -> str:
    width = f"({hi} - {lo})"
    if curve == "unif":
        value = f"({lo} + ({y}) * {width})"
    elif curve == "kuma":
        value = f"({lo} + {kuma_inverse(y, p0, p1)} * {width})"
    else:
        low, high = raw(curve, f"{lo} / {width}", p0, p1), raw(curve, f"{hi} / {width}", p0, p1)
        value = f"({width} * {raw_inverse(curve, f'(({high} - {low}) * ({y}) + {low})', p0, p1)})"
    return f"(CASE WHEN {width} > 0 THEN {value} ELSE {lo} END)"


def code(curve: str, bits: int = 8, p0: float | str = 1.0, p1: float | str = 1.0, x: str = "value", lo: str = "lo", hi: str = "hi") -> str:
    top = 2**bits - 1
    return f"CAST(greatest(least(floor({top} * {bend(curve, x, lo, hi, p0, p1)} + 0.5), {top}), 0) AS INTEGER)"


def error(curve: str, bits: int, p0: float | str = 1.0, p1: float | str = 1.0, coded: str = "code", x: str = "value") -> str:
    """Squared error of a value whose code is in a column already."""
    return f"pow({x} - {unbend(curve, f'(CAST({coded} AS DOUBLE) / {2**bits - 1})', p0=p0, p1=p1)}, 2)"


def r6(x: str, places: int = 6) -> str:
    return f"(round({x}, {places}) + 0.0)"


LONG = (
    "long AS (SELECT vec_id, CAST(list_min(embedding) AS DOUBLE) AS lo, CAST(list_max(embedding) AS DOUBLE) AS hi, "
    "CAST(unnest(embedding) AS DOUBLE) AS value, unnest(range(len(embedding))) AS dim FROM embeddings)"
)
DOT = "list_sum(list_transform(list_zip({a}, {b}), lambda p: CAST(p[1] AS DOUBLE) * CAST(p[2] AS DOUBLE)))"
SQUARES = "list_sum(list_transform(list_zip({a}, {b}), lambda p: pow(CAST(p[1] AS DOUBLE) - CAST(p[2] AS DOUBLE), 2)))"
