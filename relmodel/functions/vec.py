"""Vector maths as column expressions (O29) and fixed weights that any engine can evaluate."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (norm(a) * norm(b))


def scale(a: Column, by: float) -> Column:
    return F.transform(a, lambda x: x * F.lit(by))


def plus(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def matvec(rows: list[list[float]], a: Column) -> Column:
    return F.array(*(dot(F.array(*map(F.lit, r)), a) for r in rows))


def softmax(a: Column) -> Column:
    e = F.transform(a, lambda x: F.exp(x - F.array_max(a)))
    return F.transform(e, lambda x: x / F.aggregate(e, F.lit(0.0), lambda s, v: s + v))


def fixed_weight(r: int, i: int, j: int) -> float:
    """Weights of the fixed-weight forward pass: sin(1 + 31 r + 7 i + j) / 4."""
    return math.sin(1 + 31 * r + 7 * i + j) / 4


def number(x: float) -> str:
    """A double literal in both SQL dialects."""
    return f"{x:.12e}"


def linear_sql(r: int, cols: list[str]) -> list[str]:
    """The rows of weight matrix r times the given columns, as SQL."""
    return [" + ".join(f"{number(fixed_weight(r, i, j))} * {c}" for j, c in enumerate(cols)) for i in range(len(cols))]


def norm_sql(cols: list[str], eps: float = 1e-5) -> list[str]:
    """Layer normalisation (no affine part) over the given columns, as SQL."""
    n = len(cols)
    mean = f"(({' + '.join(cols)}) / {n})"
    var = f"(({' + '.join(f'({c} - {mean}) * ({c} - {mean})' for c in cols)}) / {n})"
    return [f"({c} - {mean}) / sqrt({var} + {number(eps)})" for c in cols]
