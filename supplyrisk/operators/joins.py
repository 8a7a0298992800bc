"""Range, theta and fuzzy joins that audits need."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

DAY = 86_400_000_000
#: Days per bin of the overlap join.
BIN_DAYS = 30

# Advisories (brand, least and greatest size) and misspelt component words.
ADVISORIES = (("Brand#1", 10, 20), ("Brand#2", 1, 5), ("Brand#3", 40, 50), ("Brand#11", 10, 20), ("Brand#23", 1, 15), ("Brand#45", 30, 50))
WORDS = (("rng", 1), ("wiget", 1), ("bolts", 1), ("blu", 1), ("smal", 1), ("gear", 2))


def overlap_exposure(supplier: DataFrame, lineitem: DataFrame, length_days: int = 90) -> DataFrame:
    """supplier_key, n_lines shipped while the supplier's breach lasted (half open).

    Breaches are cut into bins of days and met on (supplier, bin); each line is in one bin,
    so a pair is found once and no pair outside shared bins is made."""
    begin = F.unix_micros(F.lit("1995-01-01").cast("timestamp")) + F.col("s_suppkey") * (20 * DAY)
    breach = supplier.select(F.col("s_suppkey").alias("supplier_key"), begin.alias("a"), (begin + length_days * DAY).alias("b"))
    bins = F.sequence(F.floor(F.col("a") / (BIN_DAYS * DAY)), F.floor((F.col("b") - 1) / (BIN_DAYS * DAY)))
    breach = breach.withColumn("bin", F.explode(bins))
    at = F.unix_micros(F.col("l_shipdate").cast("timestamp"))
    line = lineitem.select(F.col("l_suppkey").alias("supplier_key"), at.alias("at"), F.floor(at / (BIN_DAYS * DAY)).alias("bin"))
    return line.join(breach, ["supplier_key", "bin"]).where("at >= a and at < b").groupBy("supplier_key").agg(F.count("*").alias("n_lines"))


def advisory(part: DataFrame, rows: tuple = ADVISORIES) -> DataFrame:
    """part_key, lo, hi of each advisory on the part's brand whose size range holds it."""
    given = F.broadcast(part.sparkSession.createDataFrame(rows, "p_brand string, lo int, hi int"))
    met = part.select("p_partkey", "p_brand", "p_size").join(given, "p_brand").where("p_size between lo and hi")
    return met.select(F.col("p_partkey").alias("part_key"), "lo", "hi")


def name_match(part: DataFrame, words: tuple = WORDS) -> DataFrame:
    """part_key, word, edits where a word of the part's name is within a few edits.

    The word list is a literal, so the nested loop is rows times its length."""
    out = None
    split = part.select("p_partkey", F.explode(F.split(F.lower("p_name"), " ")).alias("own"))
    for word, most in words:
        edits = F.levenshtein("own", F.lit(word))
        got = split.select("p_partkey", F.lit(word).alias("word"), edits.alias("edits")).where(F.col("edits") <= most)
        out = got if out is None else out.unionAll(got)
    return out.groupBy(F.col("p_partkey").alias("part_key"), "word").agg(F.min("edits").alias("edits"))
