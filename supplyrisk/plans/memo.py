"""Results shared by the queries of one session, by application, folder and name."""

from __future__ import annotations

from collections.abc import Callable
from typing import TypeVar

from pyspark.sql import SparkSession

T = TypeVar("T")
_kept: dict[tuple, object] = {}


def memo(spark: SparkSession, sf_dir: str, name: object, make: Callable[[], T]) -> T:
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _kept:
        _kept[key] = make()
    return _kept[key]  # type: ignore[return-value]


def forget(keep: tuple[str, ...] = ()) -> None:
    """Drop what is kept, but for the given kinds (first words of names)."""
    for key in list(_kept):
        kind = key[2][0] if isinstance(key[2], tuple) else key[2]
        if kind not in keep:
            del _kept[key]
