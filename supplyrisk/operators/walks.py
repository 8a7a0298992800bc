"""Reach, ranks, cycles and components of compiled edges."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from supplyrisk.operators import gathered, kernels
from supplyrisk.operators.blocks import Blocks
from supplyrisk.operators.propagate import RunOptions
from supplyrisk.plans.staging import Staged


def reach(prop: DataFrame, start: DataFrame, direction: str = "forward", need: int = 3, max_hops: int | None = None, options: RunOptions | None = None, distributed: bool | None = None) -> DataFrame:
    """start, vid, hops (fewest) for each pair; the start itself has 0.

    start: `start` and optionally `need` (mask bits, any of which lets a start through an
    edge). Pairs can be many: the loop keeps them distributed; a graph and start set of
    checked size are finished in one task."""
    options = options or RunOptions()
    begin = start.select("start", (F.col("need") if "need" in start.columns else F.lit(need)).cast("long").alias("need")).distinct()
    backward = direction == "backward"
    if distributed is None:
        distributed = prop.count() > options.local_cap or begin.count() > 1000
    if not distributed:
        out = kernels.reach_in_one_task(prop, begin, backward)
        return out if max_hops is None else out.where(F.col("hops") <= max_hops)
    a, b = ("dst", "src") if backward else ("src", "dst")
    edges = prop.select(F.col(a).alias("vid"), F.col(b).alias("next"), "mask")
    seen = Staged(begin.select("start", "need", F.col("start").alias("vid"), F.lit(0).cast("long").alias("hops")), "reach")
    frontier, everything = seen.df, seen.df
    for hop in range(1, (max_hops if max_hops is not None else options.max_rounds) + 1):
        new = frontier.join(edges, "vid").where(F.col("mask").bitwiseAND(F.col("need")) != 0).select("start", "need", F.col("next").alias("vid")).distinct()
        new = new.join(everything.select("start", "vid"), ["start", "vid"], "left_anti").withColumn("hops", F.lit(hop).cast("long"))
        step = Staged(new.select("start", "need", "vid", "hops"), "reach")
        if not step.df.limit(1).count():
            break
        frontier, everything = step.df, everything.unionAll(step.df)
        if hop % options.compact_every == 0:
            everything = Staged(everything, "reach").df
    return everything.select("start", "vid", "hops")


def topo_levels(prop: DataFrame, vertices: DataFrame, options: RunOptions | None = None, distributed: bool | None = None, laid: Blocks | None = None) -> DataFrame:
    """vid, level: longest path from a vertex without in-edges; null on and behind cycles.

    laid: the same edges and vertices by blocks, ranked by numbers if they are few enough for one task."""
    options = options or RunOptions()
    if laid is not None and not distributed and gathered.number(laid).m <= options.gather_cap:
        return gathered.ranks(laid)
    if distributed is None:
        distributed = prop.count() > options.local_cap
    if not distributed:
        got = kernels.levels_in_one_task(prop, vertices)
        return got.select("vid", F.when(F.col("level") >= 0, F.col("level")).alias("level"))
    edges = Staged(prop.select("src", "dst"), "peel").df
    waits = edges.groupBy("dst").agg(F.count("*").alias("n"))
    waits = Staged(vertices.select("vid").join(waits.withColumnRenamed("dst", "vid"), "vid", "left").select("vid", F.coalesce("n", F.lit(0)).alias("n")), "peel").df
    done, level = None, 0
    while True:
        free = Staged(waits.where("n = 0").select("vid", F.lit(level).cast("long").alias("level")), "peel").df
        if not free.limit(1).count():
            break
        done = free if done is None else done.unionAll(free)
        lost = edges.join(free.select(F.col("vid").alias("src")), "src").groupBy("dst").agg(F.count("*").alias("less")).withColumnRenamed("dst", "vid")
        waits = Staged(waits.where("n > 0").join(lost, "vid", "left").select("vid", (F.col("n") - F.coalesce("less", F.lit(0))).alias("n")), "peel").df
        level += 1
    left = waits.select("vid", F.lit(None).cast("long").alias("level"))
    return left if done is None else done.unionAll(left)


def find_cycles(prop: DataFrame, vertices: DataFrame, options: RunOptions | None = None) -> DataFrame:
    """vid of what is left when vertices without in-edges, then without out-edges, are peeled."""
    behind = topo_levels(prop, vertices, options).where("level is null").select("vid")
    behind = Staged(behind, "residue").df
    inner = prop.join(behind.withColumnRenamed("vid", "src"), "src", "left_semi").join(behind.withColumnRenamed("vid", "dst"), "dst", "left_semi")
    back = inner.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "mask")
    return topo_levels(back, behind, options).where("level is null").select("vid")


def components(prop: DataFrame, vertices: DataFrame, options: RunOptions | None = None) -> DataFrame:
    """vid, component (smallest vid) of weakly connected parts, by alternating stars."""
    options = options or RunOptions()
    edges = Staged(prop.where("src <> dst").select(F.greatest("src", "dst").alias("a"), F.least("src", "dst").alias("b")).distinct(), "stars").df
    for _ in range(options.max_rounds):
        both = edges.select(F.col("a").alias("u"), F.col("b").alias("v")).unionAll(edges.select("b", "a"))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        down = large.join(large.groupBy("a").agg(F.min("b").alias("m")), "a")
        new = Staged(down.select(F.col("b").alias("a"), F.col("m").alias("b")).unionAll(down.select("a", F.col("m").alias("b"))).where("a <> b").distinct(), "stars").df
        crossing = new.join(new.select(F.col("b").alias("a")).distinct(), "a", "left_semi").limit(1).count()
        several = 0 if crossing else new.groupBy("a").count().where("count > 1").limit(1).count()
        edges = new
        if not crossing and not several:
            break
    return vertices.select("vid").join(edges.select(F.col("a").alias("vid"), F.col("b").alias("root")), "vid", "left").select("vid", F.coalesce("root", "vid").alias("component"))
