"""Helpers shared by the training-data operators: staging, ranges, ranks."""

from __future__ import annotations

import math
from collections import Counter

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from supplyrisk.plans.staging import Staged, delete, partitions, shared_dir, stage
from supplyrisk.sources.tables import table

__all__ = ["Staged", "bucket_count", "bucket_of", "delete", "key_bounds", "order_key", "partitions", "range_of", "shared_dir", "stage", "table"]

#: Rows of a narrow table that one range bucket should hold, and the most buckets there are
#: (their bounds are part of the plan).
ROWS_PER_BUCKET, MAX_BUCKETS = 100_000, 20_000
#: Sort key of a null id; it comes before every id.
NULL_KEY = -(2**63)


def _percentiles(keys: DataFrame, col: str, n_buckets: int) -> list[int]:
    if n_buckets < 2:
        return []
    steps = ", ".join(repr(i / n_buckets) for i in range(1, n_buckets))
    got = keys.agg(F.expr(f"percentile_approx({col}, array({steps}), {max(10_000, 10 * n_buckets)})").alias("b")).first()["b"]
    return sorted(got or [])


def key_bounds(keys: DataFrame, col: str, n_buckets: int) -> list[int]:
    """Ascending cut points of about equal counts; one bounded sketch, no sort."""
    return sorted(set(_percentiles(keys, col, n_buckets)))


def range_of(rows: DataFrame, col: str, n_buckets: int, part: Column) -> Column:
    """Number of each row's range, in the order of (col, part), of about equal counts.

    part: from 0 to below 1, not falling in the order of rows with equal keys; a key that
    holds several buckets' rows (null ids, say) is cut by it, so that it isn't one range."""
    got = _percentiles(rows, col, n_buckets)
    times = Counter(got)
    bounds, most = sorted(times), max(times.values(), default=1)
    at = bucket_of(F.col(col), bounds)
    if most == 1:
        return at.cast("long")
    held = F.array(*[F.lit(times[b]) for b in bounds])
    same = F.get(F.array(*[F.lit(b).cast("long") for b in bounds]), at - 1) == F.col(col)
    n = F.get(held, at - 1)
    inside = F.when(at == 0, 0).when(same, F.least(F.floor(part * n), n - 1)).otherwise(n)
    return at.cast("long") * (most + 1) + inside


def bucket_of(key: Column, bounds: list[int]) -> Column:
    """How many bounds are at or below the key: a binary search in powers of two."""
    if not bounds:
        return F.lit(0)
    cuts = F.array(*[F.lit(b).cast("long") for b in bounds])
    top = 1 << (len(bounds).bit_length() - 1)
    steps = F.array(*[F.lit(top >> i) for i in range(top.bit_length())])
    return F.aggregate(
        steps,
        F.lit(0),
        lambda at, step: F.when((at + step <= len(bounds)) & (F.try_element_at(cuts, at + step) <= key), at + step).otherwise(at),
    )


def bucket_count(n_rows: int, at_least: int) -> int:
    return max(1, min(max(at_least, math.ceil(n_rows / ROWS_PER_BUCKET)), max(1, n_rows), MAX_BUCKETS))


def order_key(col: str) -> Column:
    return F.coalesce(F.col(col).cast("long"), F.lit(NULL_KEY))
