"""Streams over split event files against their batch twins."""

import datetime as dt
import time

import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

from supplyrisk.operators import propagate
from supplyrisk.plans.compile import compile_graph
from supplyrisk.sources import build, feed, tables
from supplyrisk.streaming import disclosures as d


@pytest.fixture(scope="module")
def events(spark, sf, tmp_path_factory):
    """The feed in four files by time, some rows twice."""
    path = str(tmp_path_factory.mktemp("feed") / "events")
    e = tables.table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    quarters = e.withColumn("q", F.ntile(4).over(Window.orderBy("ts")))
    for q in range(1, 5):
        part = quarters.where(F.col("q") == q).drop("q")
        part.unionAll(part.where("event_id % 10 = 0")).coalesce(1).write.mode("append").parquet(path)
    return path, e


def _drain(stream, name, mode, spark, tmp_path):
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
    q.awaitTermination(240)
    return spark.table(name)


def test_windows_match_batch(spark, sf, events, tmp_path):
    path, static = events
    n_parts, n_suppliers = (tables.table(spark, sf, t).count() for t in ("part", "supplier"))
    stream = d.facts(d.read_events(spark, path), n_parts, n_suppliers)
    got = _drain(d.windowed(stream, "1 day"), "tumbling", "append", spark, tmp_path)
    want = d.windowed(feed.facts(static, n_parts, n_suppliers), "1 day")
    last = got.agg(F.max("stop")).first()[0]
    assert last > dt.datetime(2024, 1, 20)
    want = {tuple(r) for r in want.collect() if r.stop <= last}
    assert {tuple(r) for r in got.collect()} == want


def test_kept_status_equals_batch(spark, sf, events, tmp_path):
    path, static = events
    n_parts, n_suppliers = (tables.table(spark, sf, t).count() for t in ("part", "supplier"))
    compiled = compile_graph(build.graph(spark, sf)).laid_out()
    kept = d.KeptStatus(compiled, f"file://{tmp_path}/status")
    stream = d.facts(d.read_events(spark, path, 2), n_parts, n_suppliers)
    d.keep_status(stream, kept, str(tmp_path / "kept")).awaitTermination(400)
    facts = feed.facts(static, n_parts, n_suppliers).where("kind in ('SV', 'HM')").select("vid", "kind").distinct()
    want = {(r.vid, r.status) for r in propagate.run(compiled.with_seeds(facts))[0].collect()}
    assert {(r.vid, r.status) for r in kept.latest(spark).collect()} == want
    # The last batch again changes nothing.
    again = stream.sparkSession.createDataFrame([], "vid long, kind string")
    kept.add(again, 1)
    assert {(r.vid, r.status) for r in kept.latest(spark).collect()} == want


def test_late_rows_are_dropped(spark, tmp_path):
    rows = lambda *x: spark.createDataFrame([(i, ts, 1, "error", 1.0, '{"k": 1}') for i, ts in x], d.EVENTS)
    path = str(tmp_path / "late-events")
    # With two stateful steps a batch drops what was late before its predecessor.
    for part in ([(1, dt.datetime(2024, 1, 1)), (2, dt.datetime(2024, 1, 10))], [(4, dt.datetime(2024, 1, 11))], [(3, dt.datetime(2024, 1, 2))], [(5, dt.datetime(2024, 1, 20))]):
        rows(*part).coalesce(1).write.mode("append").parquet(path)
        time.sleep(1.1)  # files are taken by their time
    got = _drain(d.windowed(d.facts(d.read_events(spark, path), 5, 5), "1 day"), "late", "append", spark, tmp_path)
    assert {r.start.day: r.n for r in got.collect()} == {1: 1, 10: 1, 11: 1}


def test_joins_sessions_and_tracking(spark, events, sf, tmp_path):
    path, static = events
    stream = lambda: d.facts(d.read_events(spark, path, 10), 7, 3)
    batch = feed.facts(static, 7, 3)
    got = _drain(d.audited(stream(), stream()), "audited", "append", spark, tmp_path)
    want = {(r.fact_id, r.audit_id) for r in d.audited(batch, batch).collect()}
    assert want and {(r.fact_id, r.audit_id) for r in got.collect()} == want
    tracked = _drain(d.track(stream()), "tracked", "update", spark, tmp_path)
    want = {r.vid: r.n for r in batch.groupBy("vid").agg(F.count("*").alias("n")).collect()}
    assert {r.vid: r.n for r in tracked.groupBy("vid").agg(F.max("n").alias("n")).collect()} == want
    runs = _drain(d.sessions(stream(), "6 hours"), "runs", "append", spark, tmp_path)
    want = {(r.vid, r.start): r.n for r in d.sessions(batch, "6 hours").collect()}
    assert all(want[r.vid, r.start] == r.n for r in runs.collect()) and runs.count() > 5
    named = _drain(d.with_names(stream(), build.graph(spark, sf).vertices), "named", "append", spark, tmp_path)
    assert named.where("kind = 'SV' and vtype = 'artifact'").count() > 0
