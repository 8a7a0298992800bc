"""Pages as artifacts fetched from web hosts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from supplyrisk.operators.graph import BuildHistory
from supplyrisk.sources.schema import PAGE, WEB_HOST, hashed, pack
from supplyrisk.sources.tables import table


def authority(url: Column) -> Column:
    return F.coalesce(F.try_parse_url(url, F.lit("HOST")), F.lit(""))


def host_id(name: Column) -> Column:
    return hashed(WEB_HOST, name)


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "pages").select("page_id", authority(F.col("url")).alias("authority"))


def graph(spark: SparkSession, sf_dir: str) -> BuildHistory:
    got = pages(spark, sf_dir)
    no = F.lit(None).cast("map<string,string>").alias("props")
    host, page = host_id(F.col("authority")), pack(PAGE, F.col("page_id"))
    vertices = got.select(page.alias("vid"), F.lit("artifact").alias("vtype"), F.concat(F.lit("W"), F.col("page_id").cast("string")).alias("akey"), no).unionAll(got.select(host.alias("vid")).distinct().select("vid", F.lit("host").alias("vtype"), F.lit(None).cast("string").alias("akey"), no))
    edges = got.select((-1 - F.col("page_id")).alias("eid"), host.alias("src"), page.alias("dst"), F.lit("fetched_from").alias("label"), no)
    return BuildHistory(vertices, edges)


def seeds(spark: SparkSession, sf_dir: str) -> DataFrame:
    bad = F.col("authority").contains("cheap-pills") | (F.length("authority") % 11 == 0)
    return pages(spark, sf_dir).where(bad).select(host_id(F.col("authority")).alias("vid"), F.lit("HM").alias("kind")).distinct()
