"""Small algebra on payloads held in maps and arrays, for display and for merging published states."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def merged_maps(a: Column, b: Column) -> Column:
    """Sum of two category maps; categories whose values cancel are gone."""
    both = F.map_zip_with(a, b, lambda _, x, y: F.coalesce(x, F.lit(0)) + F.coalesce(y, F.lit(0)))
    return F.map_filter(both, lambda _, v: v != 0)


def added_arrays(a: Column, b: Column) -> Column:
    """Entrywise sum of two blocks of one length."""
    return F.zip_with(a, b, lambda x, y: x + y)


def scaled(a: Column, by: Column) -> Column:
    return F.transform(a, lambda x: x * by)


def outer(a: Column, b: Column) -> Column:
    """All products of two vectors, row by row."""
    return F.flatten(F.transform(a, lambda x: F.transform(b, lambda y: x * y)))
