"""The disclosure feed as a stream: parsing, windows, joins, tracking, and kept statuses."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from supplyrisk.operators import incremental
from supplyrisk.plans.compile import Compiled
from supplyrisk.sources import feed

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
WATERMARK = "1 day"


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def facts(events: DataFrame, n_parts: int, n_suppliers: int, watermark: str = WATERMARK) -> DataFrame:
    """event_id, ts, kind, vid, severity; each event once, late ones beyond the watermark dropped."""
    return feed.facts(events, n_parts, n_suppliers).withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def windowed(stream: DataFrame, length: str, slide: str | None = None) -> DataFrame:
    """start, stop, kind, n in tumbling or sliding windows; emitted once the watermark passes."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return stream.groupBy(w, "kind").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), F.col("window.end").alias("stop"), "kind", "n")


def sessions(stream: DataFrame, gap: str) -> DataFrame:
    """start, stop, vid, n of runs of disclosures about one vertex."""
    w = stream.groupBy(F.session_window("ts", gap), "vid").agg(F.count("*").alias("n"))
    return w.select(F.col("session_window.start").alias("start"), F.col("session_window.end").alias("stop"), "vid", "n")


def with_names(stream: DataFrame, vertices: DataFrame) -> DataFrame:
    """Stream-static join: facts with the type and identity of what they are about."""
    return stream.join(vertices.select("vid", "vtype", "akey"), "vid", "left")


def audited(weak: DataFrame, audits: DataFrame, within: str = "2 days") -> DataFrame:
    """Stream-stream join: a weak part's disclosure and audit reports soon after it.

    Both sides carry watermarks, so state older than the interval is dropped."""
    a = weak.where("kind = 'SV'").select(F.col("vid"), F.col("ts").alias("ts"), F.col("event_id").alias("fact_id"))
    b = audits.where("kind = 'audit'").select(F.col("vid").alias("audit_vid"), F.col("ts").alias("audit_ts"), F.col("event_id").alias("audit_id"))
    near = F.expr(f"vid = audit_vid AND audit_ts >= ts AND audit_ts <= ts + INTERVAL {within}")
    return a.join(b, near).select("vid", "fact_id", "audit_id", "ts", "audit_ts")


TRACK = "vid long, n long, worst int, last timestamp"


def track(stream: DataFrame) -> DataFrame:
    """Per vertex, running number of incidents, worst severity and last time, one row a batch."""

    def run(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, worst, last = state.get if state.exists else (0, 0, None)
        for pdf in batches:
            n += len(pdf)
            worst = max(worst, int(pdf["severity"].fillna(0).max()))
            newest = pdf["ts"].max()
            last = newest if last is None or newest > last else last
        state.update((n, worst, last))
        yield pd.DataFrame({"vid": [key[0]], "n": [n], "worst": [worst], "last": [last]})

    return stream.groupBy("vid").applyInPandasWithState(run, TRACK, "n long, worst int, last timestamp", "update", GroupStateTimeout.NoTimeout)


@dataclass
class KeptStatus:
    """Statuses kept under path, one version per batch; a batch run again writes its version again."""

    compiled: Compiled
    path: str

    def version(self, batch: int) -> str:
        return f"{self.path}/batch={batch}"

    def latest(self, spark: SparkSession, before: int | None = None) -> DataFrame:
        jvm = spark.sparkContext._jvm
        root = jvm.org.apache.hadoop.fs.Path(self.path)
        fs = root.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        found = [] if not fs.exists(root) else [int(x.getPath().getName().split("=")[1]) for x in fs.listStatus(root) if fs.exists(jvm.org.apache.hadoop.fs.Path(x.getPath(), "_SUCCESS"))]
        found = [b for b in found if before is None or b < before]
        return spark.read.schema("vid long, status int").parquet(self.version(max(found))) if found else spark.createDataFrame([], "vid long, status int")

    def add(self, batch: DataFrame, number: int) -> None:
        """foreachBatch: only what the new facts raise is worked on."""
        spark = batch.sparkSession
        new = batch.where(F.col("kind").isin("SV", "SM", "HV", "HM")).select("vid", "kind").distinct()
        state = incremental.update(self.latest(spark, number), self.compiled, new)
        state.write.mode("overwrite").parquet(self.version(number))


def keep_status(stream: DataFrame, kept: KeptStatus, checkpoint: str, once: bool = True):
    """Start the query that keeps statuses up to date with the feed."""
    writer = stream.writeStream.foreachBatch(kept.add).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if once else writer.trigger(processingTime="1 minute")).start()
