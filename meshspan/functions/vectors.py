"""Vector expressions on ARRAY<DOUBLE> columns, built from higher-order SQL functions (no Python per row)."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def vec_dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, v: s + v)


def vec_norm(a: Column) -> Column:
    return F.sqrt(vec_dot(a, a))


def vec_scale(a: Column, s: Column) -> Column:
    return F.transform(a, lambda x: x * s)


def vec_axpy(s: Column, a: Column, b: Column) -> Column:
    """s * a + b"""
    return F.zip_with(a, b, lambda x, y: s * x + y)


def vec_outer(a: Column, b: Column) -> Column:
    """Outer product as an array of rows."""
    return F.transform(a, lambda x: F.transform(b, lambda y: x * y))


def mat_vec(rows: Column, a: Column) -> Column:
    """Matrix (array of rows) times vector."""
    return F.transform(rows, lambda row: vec_dot(row, a))


def mat_literal(matrix) -> Column:
    """A small matrix as a constant array of rows."""
    return F.array(*[F.array(*[F.lit(float(v)) for v in row]) for row in matrix])


def md5_fraction(*parts: Column) -> Column:
    """Number in [0, 1) from the first eight hexadecimal digits of an md5: the same in any engine."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 8), 16, 10).cast("double") / float(1 << 32)
