"""The ordered statuses and the algebra of verdicts."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SAFE, VULNERABLE, MALICIOUS = 0, 1, 2
NAMES = ("safe", "vulnerable", "malicious")
HOST_NAMES = ("safe", "vulnerable", "compromised")
SETS = ("sv", "sm", "hv", "hm")


def status_name(level: Column, names: tuple[str, ...] = NAMES) -> Column:
    return F.when(level == 0, names[0]).when(level == 1, names[1]).when(level == 2, names[2])


def status_level(name: Column) -> Column:
    """Level of a status word; compromised is the top level, other words are null."""
    word = F.lower(F.trim(name))
    return F.when(word == "safe", 0).when(word == "vulnerable", 1).when(word.isin("malicious", "compromised"), 2)


def max_status(*levels: Column) -> Column:
    """Greatest of the given levels; null if there is none (the maximum of no status)."""
    return F.greatest(*levels) if len(levels) > 1 else levels[0] if levels else F.lit(None).cast("int")


def merge(status: Column, *verdicts: Column) -> Column:
    """A verdict struct: the given status and the union of each of the four sets."""
    empty = F.array().cast("array<long>")
    sets = [F.array_sort(F.array_distinct(F.flatten(F.array(*[F.coalesce(v[s], empty) for v in verdicts])))).alias(s) for s in SETS]
    return F.struct(status.alias("status"), *sets)
