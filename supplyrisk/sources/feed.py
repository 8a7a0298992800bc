"""Events as a feed of disclosures about parts and suppliers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from supplyrisk.sources.schema import BASE, STORAGE, pack

#: Withdrawals and audit reports are about parts, like the facts they follow.
KINDS = {"error": "SV", "signup": "HM", "purchase": "retract", "click": "audit"}


def facts(events: DataFrame, n_parts: int, n_suppliers: int) -> DataFrame:
    """event_id, ts, kind, vid, severity; works on streams. Breaches are thinned by value."""
    kind = F.when(F.col("event_type") == "error", "SV").when((F.col("event_type") == "signup") & (F.col("value") > 150), "HM").when(F.col("event_type") == "purchase", "retract").when(F.col("event_type") == "click", "audit")
    vid = F.when(kind == "HM", pack(STORAGE, F.col("user_id") % n_suppliers)).otherwise(pack(BASE, F.col("user_id") % n_parts))
    severity = F.get_json_object("props", "$.k").try_cast("int")
    return events.select("event_id", F.col("ts").cast("timestamp").alias("ts"), kind.alias("kind"), vid.alias("vid"), severity.alias("severity")).where("kind is not null")


def order_time(ts: F.Column) -> F.Column:
    """Feed time stretched over the years of the orders: 80 days for each day of the feed."""
    seconds = (F.unix_micros(ts) - F.unix_micros(F.lit("2024-01-01").cast("timestamp"))) * 80
    return F.timestamp_micros(F.unix_micros(F.lit("1995-01-01").cast("timestamp")) + seconds)
