"""Columns that prepare values for dependencies."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def normalised(c: Column) -> Column:
    """Text without case, outer and repeated white space."""
    return F.regexp_replace(F.trim(F.lower(c)), r"\s+", " ")


def host(url: Column) -> Column:
    return F.regexp_extract(url, "^[a-z]+://([^/?#]+)", 1)


def map_key(c: Column) -> Column:
    """A map as a sorted list of entries, which can be compared and grouped."""
    return F.array_sort(F.map_entries(c))


def zero(c: Column) -> Column:
    """A double with one kind of zero."""
    return F.when(c == 0, F.lit(0.0)).otherwise(c)
