"""Streams and small expressions written once and read alike by Spark SQL and by the SQL oracle.

Everything here is integer arithmetic on BIGINT, so results do not depend on engine, partitioning or order.
"""

from __future__ import annotations

import math

P = 2147483647  # products of two residues stay below 2^62
MICRO = 1_000_000


def mix(x: str, c: int) -> str:
    return f"(((({x}) % {P}) * (({x}) % {P}) + {c}) % {P})"


def stream(id_: str, salt: int) -> str:
    """A pseudo-random BIGINT in [0, P) for an id expression: two rounds of the quadratic map."""
    return mix(mix(f"(({id_}) * 48271 + {salt})", 12345), 777)


def permille(id_: str, salt: int) -> str:
    return f"({stream(id_, salt)} % 1000)"


def inline_table(spark, rows, schema: str):
    """A short literal table as part of the plan: no job, no Python rows. `schema`: 'name type, ...'."""
    fields = [f.strip().split(" ", 1) for f in schema.split(",")]

    def cell(v):
        if v is None:
            return "NULL"
        if isinstance(v, str):
            return "'" + v.replace("\\", "\\\\").replace("'", "\\'") + "'"
        return str(v).lower() if isinstance(v, bool) else repr(v)

    casts = ", ".join(f"CAST(col{i + 1} AS {kind}) AS `{name}`" for i, (name, kind) in enumerate(fields))
    body = ", ".join("(" + ", ".join(map(cell, r)) + ")" for r in rows) or "(" + ", ".join(["NULL"] * len(fields)) + ")"
    return spark.sql(f"SELECT {casts} FROM VALUES {body}" + ("" if rows else " WHERE false"))


def incomplete_beta(a: float, b: float, x: float) -> float:
    """Regularised incomplete beta function by its continued fraction."""
    if x <= 0 or x >= 1:
        return float(x >= 1)
    if x > (a + 1) / (a + b + 2):
        return 1 - incomplete_beta(b, a, 1 - x)
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x)) / a
    value = 0.0
    for m in range(200, 0, -1):  # evaluated from the far end, so no safeguards against zero divisors are needed
        even = m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m))
        odd = -(a + m - 1) * (a + b + m - 1) * x / ((a + 2 * m - 2) * (a + 2 * m - 1))
        value = odd / (1 + even / (1 + value))
    return front / (1 + value)


def beta_knots(mean: float, total: float = 4.0, pieces: int = 100) -> list[int]:
    """Quantiles i / pieces of the Beta law with this mean and parameter sum, in micro-units."""
    a, b = total * mean, total * (1 - mean)
    out = [0]
    for i in range(1, pieces):
        lo, hi = 0.0, 1.0
        for _ in range(60):
            mid = (lo + hi) / 2
            lo, hi = (mid, hi) if incomplete_beta(a, b, mid) < i / pieces else (lo, mid)
        out.append(round(MICRO * (lo + hi) / 2))
    return [*out, MICRO]


def knot_lookup(array: str, u: str, pieces: int = 100, spark: bool = False) -> str:
    """Linear interpolation in an array of knots at u in [0, P), integers throughout. The two engines differ in how they index and divide."""
    at = f"({u} * {pieces} div {P})" if spark else f"({u} * {pieces} // {P})"
    rest = f"(({u} * {pieces} % {P}) div 1000)" if spark else f"(({u} * {pieces} % {P}) // 1000)"
    get = (lambda i: f"{array}[cast({i} as int)]") if spark else (lambda i: f"{array}[{i} + 1]")
    step = f"(({get(at + ' + 1')} - {get(at)}) * {rest})"
    whole = P // 1000
    return f"({get(at)} + " + (f"{step} div {whole})" if spark else f"{step} // {whole})")
