"""Vector arithmetic on ``array<double>`` columns and on scalar column bundles.

Aggregations run on ``d`` scalar columns, so sums combine on the map side and stay in generated code; arrays
appear only where tables meet.
"""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    """Cosine; null if either vector is zero."""
    size = norm(a) * norm(b)
    return F.when(size > 0, dot(a, b) / size)


def axpy(scale: Column | float, x: Column, y: Column) -> Column:
    """scale * x + y."""
    s = scale if isinstance(scale, Column) else F.lit(scale)
    return F.zip_with(x, y, lambda a, b: s * a + b)


def scaled(a: Column, s: Column) -> Column:
    return F.transform(a, lambda x: x * s)


def parts(a: str, d: int) -> list[Column]:
    """The components of an array column."""
    return [F.col(a)[i] for i in range(d)]


def sums(a: str, d: int, weight: Column | None = None) -> list[Column]:
    """Aggregates ``__s0`` to ``__s{d-1}``: sums of components, weighted on demand."""
    return [F.sum(x if weight is None else x * weight).alias(f"__s{i}") for i, x in enumerate(parts(a, d))]


def means(a: str, d: int) -> list[Column]:
    return [F.avg(x).alias(f"__s{i}") for i, x in enumerate(parts(a, d))]


def gathered(d: int, by: Column | None = None) -> Column:
    """The array of ``__s`` columns, divided by ``by`` on demand."""
    columns: Iterable[Column] = (F.col(f"__s{i}") for i in range(d))
    return F.array(*(c if by is None else c / by for c in columns))


def half_up(x: Column, digits: int = 6) -> Column:
    """``x`` rounded by its binary value, as DuckDB does: scaled, rounded to a whole number with halves away from zero, scaled back.

    ``F.round`` looks at the shortest decimal text instead, which differs where that text ends in a half and the binary value lies below it.
    """
    return F.round(x * 10.0**digits) / 10.0**digits


def rounded(a: Column, digits: int = 6) -> Column:
    return F.transform(a, lambda x: half_up(x, digits) + 0.0)
