"""Dotted versions and name matching."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def compare(a: Column, b: Column) -> Column:
    """-1, 0 or 1; versions are dotted integers, missing or non-numeric places count 0."""
    x, y = (F.transform(F.split(F.coalesce(v, F.lit("")), r"\."), lambda p: F.coalesce(p.try_cast("long"), F.lit(0).cast("long"))) for v in (a, b))
    n = F.greatest(F.size(x), F.size(y))
    zeros = F.array_repeat(F.lit(0).cast("long"), n)
    x, y = F.slice(F.concat(x, zeros), 1, n), F.slice(F.concat(y, zeros), 1, n)
    return F.when(x < y, -1).when(x > y, 1).otherwise(0)


def word(text: Column, number: int) -> Column:
    return F.try_element_at(F.split(text, " "), F.lit(number))
