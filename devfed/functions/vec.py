"""Vectors as array<double> columns, in expressions of the engine (no Python on rows)."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Margins are clipped to this before exponentials.
CLIP = 30.0


def _total(array: Column) -> Column:
    return F.aggregate(array, F.lit(0.0), lambda s, x: s + x)


def literal(values: Sequence[float]) -> Column:
    return F.array(*(F.lit(float(v)) for v in values))


def dot(a: Column, b: Column) -> Column:
    return _total(F.zip_with(a, b, lambda x, y: x * y))


def scale(a: Column, by: Column | float) -> Column:
    by = by if isinstance(by, Column) else F.lit(float(by))
    return F.transform(a, lambda x: x * by)


def add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def sub(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x - y)


def axpy(alpha: Column | float, x: Column, y: Column) -> Column:
    """alpha * x + y."""
    return add(scale(x, alpha), y)


def norm2(a: Column) -> Column:
    return F.sqrt(_total(F.transform(a, lambda x: x * x)))


def dist2(a: Column, b: Column) -> Column:
    return norm2(sub(a, b))


def mean(a: Column) -> Column:
    return _total(a) / F.size(a)


def margin(columns: Sequence[str], w: Sequence[float], intercept: bool = True) -> Column:
    """The linear score of wide columns, unrolled so that it stays in generated code; w begins with the intercept."""
    w = [float(x) for x in w]
    out = F.lit(w[0]) if intercept else F.lit(0.0)
    for c, x in zip(columns, w[1:] if intercept else w, strict=True):
        out = out + F.col(c) * F.lit(x)
    return out


def sigmoid(z: Column) -> Column:
    return F.lit(1.0) / (F.lit(1.0) + F.exp(-F.greatest(F.least(z, F.lit(CLIP)), F.lit(-CLIP))))


def tidy(c: Column, digits: int = 6) -> Column:
    """Rounded, without a negative zero."""
    return F.round(c, digits) + F.lit(0.0)
