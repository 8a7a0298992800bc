"""Temporal and graded rules: what the plain calculus leaves to later work."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from supplyrisk.functions.rules import passed
from supplyrisk.operators import gathered
from supplyrisk.operators.propagate import RunOptions
from supplyrisk.plans.compile import LABELS, Compiled
from supplyrisk.plans.staging import Staged


def temporal_edges(prop: DataFrame, use: DataFrame, facts: DataFrame) -> DataFrame:
    """Edges of prop that a timed fact may act through. facts: vid, from_ts, to_ts of breached
    sources; use: src, dst, used_at. An edge from a timed source stays if some use of it lies
    in one of its intervals (half open); other edges stay."""
    timed = facts.select(F.col("vid").alias("src")).distinct()
    free = prop.join(timed, "src", "left_anti")
    active = use.join(facts.withColumnRenamed("vid", "src"), "src").where("used_at >= from_ts and used_at < to_ts").select("src", "dst").distinct()
    bound = prop.join(timed, "src", "left_semi").join(active, ["src", "dst"], "left_semi")
    return free.select(*prop.columns).unionAll(bound.select(*prop.columns))


def temporal_status(compiled: Compiled, use: DataFrame, facts: DataFrame, options: RunOptions | None = None) -> DataFrame:
    """vid, status where timed facts act only as temporal_edges says. If no edge enters a timed source, its status is its
    fact's, so what it hands over its active edges are facts of their ends and the edges need not be laid out again."""
    from supplyrisk.operators import propagate

    timed = facts.select("vid").distinct()
    if compiled.prop.join(timed.withColumnRenamed("vid", "dst"), "dst", "left_semi").limit(1).count():
        kept = temporal_edges(compiled.prop, use, facts)
        return propagate.run(replace(compiled, prop=kept, n_edges=None, buckets=None, packed=None, masks=None, blocks=None), "auto", options)[0]
    seeds = compiled.seeds.groupBy("vid").agg(F.max("status").alias("status"))
    own = Staged(seeds.join(timed, "vid", "left_semi"), "timed").df
    out = compiled.prop.select("src", "dst", "mask", "label").join(timed.withColumnRenamed("vid", "src"), "src", "left_semi")
    active = temporal_edges(out, use, facts).join(own.withColumnRenamed("vid", "src"), "src")
    handed = active.select(F.col("dst").alias("vid"), passed(F.col("status"), F.col("mask")).alias("status")).where("status > 0")
    start = Staged(seeds.join(timed, "vid", "left_anti").unionAll(handed).groupBy("vid").agg(F.max("status").alias("status")), "timed").df
    return propagate.run(replace(compiled, seeds=start), "auto", options)[0].unionAll(own)


def graded(compiled: Compiled, scores: DataFrame, by_label: dict[str, float], label: str, factors: DataFrame, options: RunOptions | None = None) -> DataFrame:
    """propagate_scored with weights by label (1 if not named), where edges of `label` are also weighed by their source's
    factor (vid, factor; 1 if it has none). A graph laid out by blocks is graded by numbers if it fits one task."""
    options = options or RunOptions()
    weights = [by_label.get(x, 1.0) for x in LABELS]
    if compiled.blocks is not None and compiled.masks is None and gathered.number(compiled.blocks).m <= options.gather_cap:
        return gathered.grades(compiled.blocks, scores, weights, LABELS.index(label), factors)
    w = F.lit(1.0)
    for name, weight in by_label.items():
        w = F.when(F.col("label") == name, weight).otherwise(w)
    w = w * F.when(F.col("label") == label, F.coalesce("factor", F.lit(1.0))).otherwise(1.0)
    prop = compiled.prop.join(factors.withColumnRenamed("vid", "src"), "src", "left").withColumn("w", w)
    return propagate_scored(replace(compiled, prop=prop, packed=None, blocks=None), scores, F.col("w"), options)


def propagate_scored(compiled: Compiled, scores: DataFrame, weight: Column | None = None, options: RunOptions | None = None) -> DataFrame:
    """vid, score: graded threat. scores: vid, score; in (0, 1] vulnerable, in (1, 2] malicious.

    An edge multiplies the part above its class's floor by `weight` (a Column over prop with
    values in (0, 1], default 1): vulnerable s goes on as s * w over PASS edges, malicious
    1 + s as 1 + s * w over all. A vertex keeps the greatest. Levels are as in the plain
    rules, since a weight never crosses the floor. A source's host weight is its repute."""
    options = options or RunOptions()
    edges = Staged(compiled.prop.select("src", "dst", "mask", (weight if weight is not None else F.lit(1.0)).cast("double").alias("w")), "scored").df
    state = Staged(scores.groupBy("vid").agg(F.max(F.col("score").cast("double")).alias("score")), "scored").df
    frontier = state
    for _ in range(options.max_rounds):
        if not frontier.limit(1).count():
            return state
        bad = F.col("score") > 1
        value = F.when(bad, 1 + (F.col("score") - 1) * F.col("w")).when(F.col("mask").bitwiseAND(F.lit(1)) != 0, F.col("score") * F.col("w"))
        # Rounded, so that equal products by different paths are one value.
        sent = frontier.withColumnRenamed("vid", "src").join(edges, "src").select(F.col("dst").alias("vid"), F.round(value, 9).alias("score")).where("score is not null").groupBy("vid").agg(F.max("score").alias("score"))
        raised = sent.join(state.select("vid", F.col("score").alias("old")), "vid", "left").where("old is null or score > old").select("vid", "score")
        frontier = Staged(raised, "scored").df
        state = Staged(state.unionAll(frontier).groupBy("vid").agg(F.max("score").alias("score")), "scored").df
    raise RuntimeError("no fixpoint")
