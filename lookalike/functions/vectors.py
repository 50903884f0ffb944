"""Array math as Column expressions.

A scalar that is computed elsewhere is spread with ``array_repeat`` and zipped in, never captured
by a lambda: Catalyst would inline its expression into the lambda and evaluate it per element.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a, b) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, v: s + v)


def norm(a) -> Column:
    return F.sqrt(dot(a, a))


def scale(a, by) -> Column:
    a = F.col(a) if isinstance(a, str) else a
    by = F.col(by) if isinstance(by, str) else by
    return F.zip_with(a, F.array_repeat(by, F.size(a)), lambda x, y: x * y)


def add(a, b) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def unit(a) -> Column:
    """``a`` at length one; a zero vector stays zero."""
    a = F.col(a) if isinstance(a, str) else a
    n = norm(a)
    return scale(a, F.when(n > 0, 1.0 / n).otherwise(F.lit(0.0)))


def cosine(a, b) -> Column:
    """Cosine of two arrays; 0 where either is zero."""
    n = norm(a) * norm(b)
    return F.when(n > 0, dot(a, b) / n).otherwise(F.lit(0.0))


def l2(a, b) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, v: s + v))


def r6(c, digits: int = 6) -> Column:
    """Rounded, and without a negative zero."""
    c = F.col(c) if isinstance(c, str) else c
    return F.round(c, digits) + F.lit(0.0)


def long_form(df, id_col: str, vec_col: str):
    """``id_col, dim, value`` rows of a vector column, values to six digits."""
    return df.select(id_col, F.posexplode(vec_col).alias("dim", "value")).select(id_col, F.col("dim").cast("int").alias("dim"), r6("value").alias("value"))
