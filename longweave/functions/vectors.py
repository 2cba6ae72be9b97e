"""Vectors in array<double> columns, by built-in functions only."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _col(c) -> Column:
    return F.col(c) if isinstance(c, str) else c


def doubles(c) -> Column:
    return _col(c).cast("array<double>")


def dot(a, b) -> Column:
    return F.aggregate(F.zip_with(_col(a), _col(b), lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def l2norm(a) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a, b) -> Column:
    """0 where either vector is zero."""
    n = l2norm(a) * l2norm(b)
    return F.when(n == 0, 0.0).otherwise(dot(a, b) / n)


def l2_distance(a, b) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(_col(a), _col(b), lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))


def axpy(k, a, b) -> Column:
    return F.zip_with(_col(a), _col(b), lambda x, y: F.lit(k) * x + y)


def mean_pair(a, b) -> Column:
    return F.zip_with(_col(a), _col(b), lambda x, y: (x + y) / 2)


def softmax(a) -> Column:
    e = F.transform(_col(a), lambda x: F.exp(x - F.array_max(_col(a))))
    return F.transform(e, lambda x: x / F.aggregate(e, F.lit(0.0), lambda s, y: s + y))


def hash_state(tok, d: int = 8, seed: int = 7) -> Column:
    """Integer-valued coordinates in [-8, 8] from md5 of token, coordinate and seed."""
    return F.transform(
        F.sequence(F.lit(0), F.lit(d - 1)),
        lambda j: (F.conv(F.substring(F.md5(F.concat(_col(tok), F.lit(":"), j.cast("string"), F.lit(f":{seed}"))), 1, 8), 16, 10).cast("long") % 17 - 8).cast("double"),
    )
