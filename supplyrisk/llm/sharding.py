"""Contiguous shards of about equal bytes from global prefix sums.

Rows are cut into ranges of the order key; the sums of the ranges give each range its
offset, a running sum inside the range gives each row its place, and the places are cut at
equal targets. All DataFrame functions; the only global window is over one row per range.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from supplyrisk.llm.common import bucket_count, partitions, range_of, stage


def prefix_sums(rows: DataFrame, key: str, sums: dict[str, str], ties: list[Column | str], part: Column) -> DataFrame:
    """rows with, for each (name, column) of sums, the sum over all rows before it.

    rows must be cheap to read twice (staged) and narrow. Order: key (a long, not null), then
    ties. part: from 0 to below 1, not falling in the order of the ties, by which rows of one
    frequent key are cut into several ranges."""
    spark = rows.sparkSession
    n = rows.count()
    dealt = rows.withColumn("__range", range_of(rows, key, bucket_count(n, partitions(spark)), part))
    totals = dealt.groupBy("__range").agg(*[F.sum(c).alias(f"__t_{name}") for name, c in sums.items()])
    before = Window.orderBy("__range").rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.select("__range", *[F.coalesce(F.sum(f"__t_{name}").over(before), F.lit(0)).alias(f"__o_{name}") for name in sums])
    inside = Window.partitionBy("__range").orderBy(key, *ties).rowsBetween(Window.unboundedPreceding, -1)
    placed = dealt.join(F.broadcast(offsets), "__range")  # one row per range, MAX_BUCKETS and their cuts at most
    placed = placed.withColumns({name: F.col(f"__o_{name}") + F.coalesce(F.sum(c).over(inside), F.lit(0)) for name, c in sums.items()})
    return placed.drop("__range", *[f"__o_{name}" for name in sums])


def stored_order(docs: DataFrame) -> Column | None:
    """Place of a row in the files it was read from, or None if docs isn't a file scan.

    Spark names part files by partition number, so this is the order they were written in."""
    try:
        docs.select("_metadata.file_name", "_metadata.row_index").schema
    except Exception as e:  # noqa: BLE001  AnalysisException of either client
        if type(e).__name__ != "AnalysisException":
            raise
        return None
    part = F.expr("try_cast(regexp_extract(_metadata.file_name, 'part-([0-9]+)', 1) as long)")
    return F.coalesce(part, F.lit(0)) * F.lit(1 << 40) + F.col("_metadata.row_index")


def shard_documents(docs: DataFrame, shards: int = 16, id_col: str = "doc_id", text_col: str = "text", order: Column | None = None) -> DataFrame:
    """doc_id, size, text_crc32, place, shard, slot of every row.

    size: UTF-8 bytes of the text (null: none) plus 1. place: the row's order key (the id,
    null ids first, unless `order` is given). A row's shard is decided by the middle of its
    bytes on the scale of all bytes, so a shard misses its target by at most half of the
    row at each end. slot: gapless from 0 inside a shard. Equal keys are ordered by
    checksum and size; repeated rows are interchangeable. Empty input: no rows."""
    key = order if order is not None else F.coalesce(F.col(id_col).cast("long"), F.lit(-(2**63)))
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    narrow = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        (F.octet_length(text).cast("long") + 1).alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"),
        key.alias("place"),
        F.lit(1).cast("long").alias("one"),
    )
    rows = stage(narrow, "shard-rows")
    placed = prefix_sums(rows, "place", {"start": "size", "number": "one"}, ties=["doc_id", "text_crc32", "size"], part=F.col("text_crc32") / 2.0**32)
    total = rows.agg(F.coalesce(F.sum("size"), F.lit(1)).alias("total"))
    cut = placed.crossJoin(F.broadcast(total)).withColumn("shard", F.least(F.lit(shards - 1), F.floor((F.col("start") + F.col("size") / 2) * shards / F.col("total"))).cast("int"))
    first = cut.groupBy("shard").agg(F.min("number").alias("first"))
    return cut.join(F.broadcast(first), "shard").select("doc_id", "size", "text_crc32", "place", "shard", (F.col("number") - F.col("first")).alias("slot"))
