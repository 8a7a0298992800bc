"""SQL functions, and Python UDFs kept off every hot path."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Row, SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import ArrayType, IntegerType, LongType, StringType, StructType


def register(spark: SparkSession) -> None:
    """status_name, status_level (SQL, inlined by the optimizer), version_cmp, merge_sets, expand_example, attack_paths."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION status_name(level INT) RETURNS STRING RETURN CASE level WHEN 0 THEN 'safe' WHEN 1 THEN 'vulnerable' WHEN 2 THEN 'malicious' END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION status_level(name STRING) RETURNS INT RETURN CASE lower(trim(name)) WHEN 'safe' THEN 0 WHEN 'vulnerable' THEN 1 WHEN 'malicious' THEN 2 WHEN 'compromised' THEN 2 END")
    spark.udf.register("version_cmp", version_cmp)
    spark.udf.register("merge_sets", merge_sets)
    spark.udtf.register("expand_example", ExpandExample)
    spark.udtf.register("attack_paths", AttackPaths)


@pandas_udf(IntegerType())
def version_cmp(a: pd.Series, b: pd.Series) -> pd.Series:
    def key(v: str | None) -> list[int]:
        out = [int(p) if p.isdigit() else 0 for p in (v or "").split(".")]
        while out and out[-1] == 0:
            out.pop()
        return out

    return pd.Series([(x > y) - (x < y) for x, y in zip(map(key, a), map(key, b), strict=True)], dtype="int32")


@pandas_udf(ArrayType(LongType()))
def merge_sets(sets: pd.Series) -> list[int]:
    """Grouped aggregate: sorted union of arrays; built-ins do this better, see lattice.merge."""
    out: set[int] = set()
    for s in sets:
        out.update(() if s is None else s)
    return sorted(out)


@udtf(returnType=StructType().add("src", LongType()).add("label", StringType()).add("dst", LongType()))
class ExpandExample:
    """The edges of the worked example, optionally of one label."""

    def eval(self, label: str) -> Iterator[tuple]:
        from supplyrisk.sources.example import EDGES

        for name, src, dst in EDGES:
            if label in ("", name):
                yield src, name, dst


@udtf(returnType=StructType().add("target", LongType()).add("fact", LongType()).add("hops", IntegerType()).add("path", StringType()))
class AttackPaths:
    """Every path without repeated vertices of at most max_hops edges from a fact to the target.

    Takes a table of edges (target, src, label, dst, and whether src is a fact), partitioned
    by target. Paths can be exponentially many in the edges: meant for the few that a bounded
    walk around a target leaves. verdict.explain lists nearest facts on graphs of any size."""

    def __init__(self) -> None:
        self.into: dict[int, list[tuple[int, str]]] = {}
        self.facts: set[int] = set()
        self.target: int | None = None
        self.max_hops = 0

    def eval(self, row: Row, max_hops: int) -> None:
        self.target, self.max_hops = row["target"], max_hops
        self.into.setdefault(row["dst"], []).append((row["src"], row["label"]))
        if row["fact"]:
            self.facts.add(row["src"])

    def terminate(self) -> Iterator[tuple]:
        if self.target is None:
            return
        open_: list[tuple[tuple[int, ...], str]] = [((self.target,), str(self.target))]
        while open_:
            path, text = open_.pop()
            if len(path) > self.max_hops:
                continue
            for src, label in self.into.get(path[0], ()):
                if src in path:
                    continue
                longer = f"{src} -{label}-> {text}"
                if src in self.facts:
                    yield self.target, src, len(path), longer
                open_.append(((src, *path), longer))
