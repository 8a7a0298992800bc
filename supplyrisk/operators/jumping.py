"""Pointer jumping: linear stretches of any length folded in a logarithm of their length.

What a vertex with one in-edge takes from it is "greatest of its own fact and what the
mask lets through". Such steps compose into steps of the same form, so every vertex of a
stretch can point two, four, eight vertices back, until it points at a vertex with several
in-edges or none.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from supplyrisk.functions.rules import PASS, passed
from supplyrisk.plans.compile import Compiled
from supplyrisk.plans.staging import Staged


def links(prop: DataFrame, facts: DataFrame) -> DataFrame:
    """vid, root, mask, base of every vertex with one in-edge: its status is the greatest of base
    and what mask lets through of the root's. root is null on cycles of such vertices and
    behind them, where base is all there is.

    prop: distinct (src, dst) with mask, no loops. facts: vid, status, one row each."""
    single = prop.groupBy("dst").agg(F.count("*").alias("n"), F.min("src").alias("root"), F.min("mask").alias("mask")).where("n = 1")
    first = single.withColumnRenamed("dst", "vid").join(facts, "vid", "left").select("vid", "root", "mask", F.coalesce("status", F.lit(0)).alias("base"))
    first = Staged(first, "links").df
    inner = first.select(F.col("vid").alias("root"))
    done = Staged(first.join(inner, "root", "left_anti").select(*first.columns), "links").df
    going = Staged(first.join(inner, "root", "left_semi").select(*first.columns), "links").df
    n = most = going.count()
    span = 1
    while n and span < most:
        ahead = done.select("*", F.lit(True).alias("ends")).unionAll(going.select("*", F.lit(False).alias("ends")))
        ahead = ahead.select(F.col("vid").alias("root"), F.col("root").alias("next"), F.col("mask").alias("further"), F.col("base").alias("there"), "ends")
        base = F.greatest("base", passed(F.col("there"), F.col("mask"))).alias("base")
        left = Observation()
        both = going.join(ahead, "root").select("vid", F.col("next").alias("root"), F.col("mask").bitwiseAND(F.col("further")).alias("mask"), base, "ends")
        step = Staged(both.observe(left, F.count_if(~F.col("ends")).alias("n")), "links").df
        done = done.unionAll(step.where("ends").drop("ends"))
        going, n, span = step.where("not ends").drop("ends"), left.get["n"], span * 2
    return done.unionAll(going.withColumn("root", F.lit(None).cast("long")))


def fold_stretches(compiled: Compiled) -> tuple[Compiled, DataFrame]:
    """The graph of the vertices with several in-edges or none, and the links of all others."""
    prop = compiled.prop.where("src <> dst").groupBy("src", "dst").agg(F.bit_or("mask").alias("mask"))
    prop = Staged(prop, "jump-edges").df
    facts = Staged(compiled.seeds.groupBy("vid").agg(F.max("status").alias("status")), "jump-facts").df
    folded = Staged(links(prop, facts), "folded").df
    into = prop.join(folded.select(F.col("vid").alias("dst")), "dst", "left_anti")
    via = folded.select(F.col("vid").alias("src"), "root", F.col("mask").alias("through"), "base")
    moved = into.join(via, "src", "left").withColumn("from", F.when(F.col("base").isNull(), F.col("src")).otherwise(F.col("root")))
    moved = Staged(moved.select("from", "dst", "mask", "through", "base"), "moved").df
    mask = F.col("mask").bitwiseAND(F.coalesce("through", F.lit(PASS))).alias("mask")
    edges = moved.where("`from` is not null and `from` <> dst").select(F.col("from").alias("src"), "dst", mask, F.lit("path").alias("label")).where("mask <> 0").distinct()
    handed = moved.where("base > 0").select(F.col("dst").alias("vid"), passed(F.col("base"), F.col("mask")).alias("status")).where("status > 0")
    own = facts.join(folded.select("vid"), "vid", "left_anti")
    seeds = own.unionAll(handed.select("vid", F.col("status").cast("int").alias("status"))).groupBy("vid").agg(F.max("status").alias("status"))
    return replace(compiled, prop=edges, seeds=seeds, n_edges=None, buckets=None, packed=None, masks=None, blocks=None), folded


def unfold(state: DataFrame, folded: DataFrame) -> DataFrame:
    """vid, status of the folded vertices that are not safe, from the others' state."""
    at = state.select(F.col("vid").alias("root"), F.col("status").alias("far"))
    status = F.greatest("base", F.coalesce(passed(F.col("far"), F.col("mask")), F.lit(0))).cast("int").alias("status")
    return folded.join(at, "root", "left").select("vid", status).where("status > 0")
