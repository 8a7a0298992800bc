"""Documents as copies of one artifact: the storage-host exception."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from supplyrisk.operators.graph import BuildHistory
from supplyrisk.operators.windows import last_before
from supplyrisk.sources.schema import DOCUMENT, SOURCE_HOST, hashed, pack
from supplyrisk.sources.tables import table


def host_id(source: Column) -> Column:
    return hashed(SOURCE_HOST, source)


def hosts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """host (vertex id), source: a row per source."""
    return table(spark, sf_dir, "documents").select("source").distinct().select(host_id(F.col("source")).alias("host"), "source")


def pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, source, previous (doc_id of the copy before), previous_source, akey."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "source", F.sha2(F.col("text").cast("binary"), 256).alias("akey"))
    got = last_before(docs, "akey", ["doc_id"], F.struct("doc_id", "source"), "before")
    return got.select("doc_id", "source", "akey", F.col("before.doc_id").alias("previous"), F.col("before.source").alias("previous_source"))


def graph(spark: SparkSession, sf_dir: str) -> BuildHistory:
    """A copy is fetched from the host to which the copy before it was published."""
    got = pairs(spark, sf_dir)
    no = F.lit(None).cast("map<string,string>").alias("props")
    doc, before = pack(DOCUMENT, F.col("doc_id")), pack(DOCUMENT, F.col("previous"))
    at = host_id(F.col("previous_source"))
    linked = got.where("previous is not null")
    edges = linked.select(before.alias("src"), at.alias("dst"), F.lit("published_to").alias("label")).unionAll(linked.select(at.alias("src"), doc.alias("dst"), F.lit("fetched_from").alias("label")))
    named = hosts(spark, sf_dir).select(F.col("host").alias("vid")).distinct()
    vertices = got.select(doc.alias("vid"), F.lit("artifact").alias("vtype"), "akey", no).unionAll(named.select("vid", F.lit("host").alias("vtype"), F.lit(None).cast("string").alias("akey"), no))
    return BuildHistory(vertices, edges.select((-1 - F.xxhash64("src", "dst", "label").bitwiseAND(F.lit(2**62 - 1))).alias("eid"), "src", "dst", "label", no))


def seeds(spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = table(spark, sf_dir, "labels")
    bad = labels.where("toxic = 1").select("doc_id").unionAll(table(spark, sf_dir, "documents").where("doc_id % 37 = 5").select("doc_id"))
    weak = labels.where("quality = 0").select("doc_id")
    vid = pack(DOCUMENT, F.col("doc_id")).alias("vid")
    return bad.select(vid, F.lit("SM").alias("kind")).unionAll(weak.select(vid, F.lit("SV").alias("kind")))
