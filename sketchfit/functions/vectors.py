"""Vector operations on ARRAY<DOUBLE> columns, all inside the JVM."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F


def as_doubles(v: Column) -> Column:
    return v.cast("array<double>")


def literal(values: Sequence[float]) -> Column:
    return F.array(*[F.lit(float(x)) for x in values])


def total(v: Column) -> Column:
    return F.aggregate(v, F.lit(0.0), lambda s, x: s + x)


def dot(a: Column, b: Column) -> Column:
    return total(F.zip_with(a, b, lambda x, y: x * y))


def dot_literal(v: Column, w: Sequence[float]) -> Column:
    """One flat expression of d products: code generation turns it into straight arithmetic."""
    out = F.get(v, F.lit(0)) * F.lit(float(w[0]))
    for i in range(1, len(w)):
        out = out + F.get(v, F.lit(i)) * F.lit(float(w[i]))
    return out


def norm2(v: Column) -> Column:
    return F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x)


def norm(v: Column) -> Column:
    return F.sqrt(norm2(v))


def scale(v: Column, c: Column | float) -> Column:
    return F.transform(v, lambda x: x * c)


def axpy(c: float, a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: F.lit(float(c)) * x + y)


def add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def subtract(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x - y)


def hadamard(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x * y)


def clip_norm(v: Column, limit: float) -> Column:
    """v, shrunk to the norm `limit` where it is longer; a zero vector stays."""
    n = norm(v)
    return scale(v, F.when(n > limit, F.lit(float(limit)) / n).otherwise(F.lit(1.0)))


def clamp(v: Column, low: Column, high: Column) -> Column:
    return F.zip_with(F.zip_with(v, low, lambda x, y: F.greatest(x, y)), high, lambda x, y: F.least(x, y))


def argmin(v: Column) -> Column:
    """0-based place of the least value, the first of equal ones."""
    return (F.array_position(v, F.array_min(v)) - 1).cast("int")


def outer_lt(v: Column, d: int) -> Column:
    """Lower triangle of v v', row by row."""
    return F.array(*[F.get(v, F.lit(a)) * F.get(v, F.lit(b)) for a in range(d) for b in range(a + 1)])


def lt_index(a: int, b: int) -> int:
    a, b = max(a, b), min(a, b)
    return a * (a + 1) // 2 + b


def fixed(x: Column, bits: int = 20) -> Column:
    """x in units of 2^-bits as an integer: floor(x * 2^bits + 1/2), the same in Spark, numpy and SQL."""
    return F.floor(x * F.lit(float(1 << bits)) + F.lit(0.5)).cast("bigint")


def micro(x: Column) -> Column:
    """x in millionths as an integer; the cut lies off the ties of decimal data, which would fall either way with the order of a sum."""
    return F.floor(x * F.lit(1e6) + F.lit(0.4637)).cast("bigint")
