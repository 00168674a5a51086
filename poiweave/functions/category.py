"""Category paths: parsing, levels, prefixes."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

LEVELS = 6


def parse(text: Column) -> Column:
    """``[a -> b -> c]`` to an array; empty text gives null."""
    inner = F.regexp_replace(F.trim(text), r"^\[|\]$", "")
    return F.when(F.length(F.trim(inner)) > 0, F.transform(F.split(inner, "->"), lambda x: F.trim(x)))


def level(path: Column, i: int) -> Column:
    """The label at level ``i`` from 1, or null."""
    return F.try_element_at(path, F.lit(i))


def truncate(path: Column, i: int) -> Column:
    return F.slice(path, 1, i)


def prefix(path: Column, i: Column | int) -> Column:
    """Identity of the first ``i`` levels."""
    return F.array_join(F.slice(path, 1, i), ">")


def key(path: Column) -> Column:
    return F.array_join(path, ">")
