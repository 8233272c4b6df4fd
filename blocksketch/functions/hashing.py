"""Seeded hash families as column expressions, and the same as SQL text for engines without xxhash64.

Portable family: arithmetic modulo P = 2**31 - 1 on endpoints reduced modulo P, so every product stays below 2**62.
x = a1 u + a2 v + b, then the quadratic c0 + c1 x + c2 x^2, all modulo P, with coefficients drawn for each (sketch, row).
The checksum has two such limbs with seeds of their own.
"""

from __future__ import annotations

import random

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..spec import SketchSpec

P = 2**31 - 1


def coefficients(seed: int, count: int, kind: str) -> list[tuple[int, ...]]:
    r = random.Random(f"{kind}/{seed}")
    return [tuple(r.randrange(1, P) for _ in range(6)) for _ in range(count)]


def _mod(x: Column) -> Column:
    return F.pmod(x, F.lit(P).cast("long"))


def _quadratic(u: Column, v: Column, c) -> Column:
    """c(i): the i-th of six coefficients as a column."""
    # generated code shares what is written twice here; a lambda would leave it
    x = _mod(_mod(_mod(u) * c(0)) + _mod(_mod(v) * c(1)) + c(2))
    return _mod(_mod(_mod(x * x) * c(3)) + _mod(x * c(4)) + c(5))


def _constant(c: tuple[int, ...]):
    return lambda i: F.lit(c[i]).cast("long")


def edge_hash(spec: SketchSpec, sk: Column, row: Column, u: Column, v: Column) -> Column:
    """31 bits for the edge in this sketch and row; 64 bits in the native family."""
    if spec.family == "native":
        return F.xxhash64(F.lit(spec.seed), sk, row, u, v)
    table = coefficients(spec.seed, spec.sketches * spec.rows, "row")
    at = (sk * spec.rows + row + 1).cast("int")
    picks = [F.element_at(F.array(*[F.lit(c[i]).cast("long") for c in table]), at) for i in range(6)]
    return _quadratic(u, v, lambda i: picks[i])


def row_constants(spec: SketchSpec, places: list[tuple[int, int]]) -> Column:
    """An array of structs (sk, row, h0..h5) for the (sketch, row) places: what with_hashes() needs, with no table of the whole sketch in the plan."""
    table = coefficients(spec.seed, spec.sketches * spec.rows, "row") if spec.family != "native" else None
    one = lambda sk, row: f"named_struct('sk', {sk}, 'row', {row}, " + ", ".join(f"'h{i}', {x}L" for i, x in enumerate(table[sk * spec.rows + row] if table else (0,) * 6)) + ")"
    return F.expr(f"array({', '.join(one(sk, row) for sk, row in places)})")


def with_hashes(df: DataFrame, spec: SketchSpec, u: str, v: str, at: str | None = "at", chk: str | None = None, out: str = "_h") -> DataFrame:
    """df with edge_hash() as the column out in the place that the struct column at names (of row_constants()), and checksum() as the column chk.

    The steps are projections of their own: an expression that holds another twice doubles the plan each time. They are
    texts, as a loop that builds many plans out of column objects spends most of its time on that.
    """
    if spec.family == "native":
        own = [f"xxhash64({spec.seed}, {at}.sk, {at}.row, {u}, {v}) as {out}"] if at else []
        return df.selectExpr("*", *own, *([f"xxhash64('chk', {spec.seed}, {u}, {v}) as {chk}"] if chk else []))
    sets = [(out, [f"{at}.h{i}" for i in range(6)])] if at else []
    if chk:
        sets += [(f"_{chk}{n}", [f"{x}L" for x in c]) for n, c in enumerate(coefficients(spec.seed, 2, "chk"))]
    mod = lambda x: f"pmod({x}, {P}L)"
    own = [f"`{c}`" for c in df.columns]
    d = df.selectExpr(*own, f"{mod(u)} as _mu", f"{mod(v)} as _mv")
    d = d.selectExpr(*own, *[mod(f"{mod(f'_mu * {c[0]}')} + {mod(f'_mv * {c[1]}')} + {c[2]}") + f" as _x{n}" for n, c in sets])
    d = d.selectExpr(*own, *[mod(f"{mod(f'{mod(f"_x{n} * _x{n}")} * {c[3]}')} + {mod(f'_x{n} * {c[4]}')} + {c[5]}") + f" as {n}" for n, c in sets])
    return d.selectExpr(*own, *([out] if at else []), *([f"_{chk}0 * {2**31}L + _{chk}1 as {chk}"] if chk else []))


def level_text(h: str, levels: int) -> str:
    """level() as text for Spark."""
    return f"cast(least(bit_count(({h} & (-{h})) - 1), {levels - 1}) as int)"


def level(h: Column, levels: int) -> Column:
    """Trailing zeros, at most levels - 1; a zero hash has 64 and so takes the top level."""
    return F.least(F.bit_count(h.bitwiseAND(-h) - 1), F.lit(levels - 1)).cast("int")


def checksum(spec: SketchSpec, u: Column, v: Column) -> Column:
    if spec.family == "native":
        return F.xxhash64(F.lit("chk"), F.lit(spec.seed), u, v)
    a, b = coefficients(spec.seed, 2, "chk")
    return _quadratic(u, v, _constant(a)) * F.lit(2**31).cast("long") + _quadratic(u, v, _constant(b))


def uniform(seed: int, kind: str, u: Column, v: Column) -> Column:
    """31 bits for the edge, the same for its insertion and deletion, independent of every row."""
    return _quadratic(u, v, _constant(coefficients(seed, 1, kind)[0]))


def poly_hash(x: Column, coeffs: list[int]) -> Column:
    """t-wise independent: a polynomial of degree t - 1 modulo P by Horner's rule."""
    x = _mod(x)
    return F.aggregate(F.array(*[F.lit(c).cast("long") for c in coeffs]), F.lit(0).cast("long"), lambda acc, c: F.pmod(acc * x + c, F.lit(P).cast("long")))


# The same expressions as SQL text.


def _sql_quadratic(u: str, v: str, c) -> str:
    x = f"((((({u}) % {P}) * {c(0)}) % {P} + ((({v}) % {P}) * {c(1)}) % {P} + {c(2)}) % {P})"
    return f"(((({x} * {x}) % {P} * {c(3)}) % {P} + ({x} * {c(4)}) % {P} + {c(5)}) % {P})"


def sql_edge_hash(spec: SketchSpec, sk: str, row: str, u: str, v: str) -> str:
    table = coefficients(spec.seed, spec.sketches * spec.rows, "row")
    return _sql_quadratic(u, v, lambda i: f"(CAST({[c[i] for c in table]} AS BIGINT[]))[({sk}) * {spec.rows} + ({row}) + 1]")


def sql_level(h: str, levels: int) -> str:
    return f"CAST(least(CASE WHEN {h} = 0 THEN 64 ELSE bit_count(({h} & (-{h})) - 1) END, {levels - 1}) AS INTEGER)"


def sql_checksum(spec: SketchSpec, u: str, v: str) -> str:
    a, b = coefficients(spec.seed, 2, "chk")
    return f"({_sql_quadratic(u, v, lambda i: str(a[i]))} * CAST({2**31} AS BIGINT) + {_sql_quadratic(u, v, lambda i: str(b[i]))})"


def sql_uniform(seed: int, kind: str, u: str, v: str) -> str:
    c = coefficients(seed, 1, kind)[0]
    return _sql_quadratic(u, v, lambda i: str(c[i]))


def sql_poly(x: str, coeffs: list[int]) -> str:
    out = "0"
    for c in coeffs:
        out = f"(({out} * (({x}) % {P}) + {c}) % {P})"
    return out
