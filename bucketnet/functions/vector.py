"""Vector and set expressions as plain Columns: they stay in the JVM, without Python rows.

A vector argument that is an expression is evaluated where it is used; pass a column of the child plan.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

GRID = 1 << 20


def _col(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x


def total(x: Column | str, start: Column | None = None) -> Column:
    return F.aggregate(_col(x), F.lit(0.0) if start is None else start, lambda a, b: a + b)


def fixed_point(x: Column | str) -> Column:
    """floor(x * 2**20) of each element as long: sums of these do not depend on their order."""
    return F.transform(_col(x), lambda v: F.floor(v.cast("double") * GRID).cast("long"))


def vec_dot(a: Column | str, b: Column | str) -> Column:
    return total(F.zip_with(_col(a), _col(b), lambda x, y: x.cast("double") * y.cast("double")))


def long_dot(a: Column | str, b: Column | str) -> Column:
    """Exact dot product of arrays of long."""
    return total(F.zip_with(_col(a), _col(b), lambda x, y: x * y), F.lit(0).cast("long"))


def vec_add(a: Column | str, b: Column | str) -> Column:
    return F.zip_with(_col(a), _col(b), lambda x, y: x + y)


def vec_scale(a: Column | str, s: Column | float) -> Column:
    return F.transform(_col(a), lambda x: x * s)


def vec_norm(a: Column | str) -> Column:
    return F.sqrt(vec_dot(a, a))


def vec_cosine(a: Column | str, b: Column | str) -> Column:
    """null where a norm is 0."""
    return F.try_divide(vec_dot(a, b), vec_norm(a) * vec_norm(b))


def vec_l2(a: Column | str, b: Column | str) -> Column:
    return F.sqrt(total(F.zip_with(_col(a), _col(b), lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double")))))


def hamming(a: Column | str, b: Column | str) -> Column:
    """Differing bits of two longs."""
    return F.bit_count(_col(a).bitwiseXOR(_col(b)))


def jaccard(a: Column | str, b: Column | str) -> Column:
    """Of two sets as arrays; null if both are empty."""
    return F.try_divide(F.size(F.array_intersect(_col(a), _col(b))).cast("double"), F.size(F.array_union(_col(a), _col(b))))


def r6(x: Column) -> Column:
    """Rounded to 6 digits, without negative zero."""
    return F.when(F.abs(x) < 5e-7, 0.0).otherwise(F.round(x, 6))


def r6_sql(x: str) -> str:
    return f"CASE WHEN abs({x}) < 5e-7 THEN 0.0 ELSE round({x}, 6) END"
