"""Small numeric column builders."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def xlog2x(x: Column) -> Column:
    """x * log2(x), 0 at 0."""
    return F.when(x > 0, x * F.log2(x)).otherwise(F.lit(0.0))


def entropy_term(p: Column) -> Column:
    """-p * log2(p), 0 at 0."""
    return -xlog2x(p)


def clip(x: Column, lo: float, hi: float) -> Column:
    return F.least(F.greatest(x, F.lit(lo)), F.lit(hi))


def safe_divide(a: Column, b: Column) -> Column:
    """a / b, 0 where b is 0."""
    return F.when(b == 0, F.lit(0.0)).otherwise(a / b)


def rounded(x: Column, digits: int = 6) -> Column:
    """Rounded, without a negative zero."""
    return F.round(x, digits) + F.lit(0.0)
