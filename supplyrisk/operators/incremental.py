"""Late facts, new edges and withdrawn facts against a kept state."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from supplyrisk.operators import blocks, gathered, propagate
from supplyrisk.plans.compile import Compiled, seed_state
from supplyrisk.plans.staging import Staged


def _raise(state: DataFrame, start: DataFrame, compiled: Compiled, options: propagate.RunOptions | None) -> DataFrame:
    """State after vertices rise to start's levels; only what rises is sent on."""
    old = state.select("vid", F.col("status").alias("old"))
    new = Staged(start.groupBy("vid").agg(F.max("status").alias("status")).join(old, "vid", "left").where("status > coalesce(old, 0)").select("vid", "status"), "raised").df
    options = options or propagate.RunOptions()
    n = compiled.n_edges if compiled.n_edges is not None else compiled.prop.count()
    if n <= options.local_cap:
        grown, _ = propagate.run(replace(compiled, seeds=state.unionAll(new), n_edges=n), "finisher", options)
        return grown
    if compiled.buckets is None:
        at = compiled.in_blocks()
        if n <= options.gather_cap:
            return gathered.solve(at.blocks, at.masks, new, state)
        return blocks.solve(at.blocks, at.masks, new, state, options.max_rounds)
    risen, _ = propagate.run(replace(compiled, seeds=new), "semi_naive", options)
    return Staged(state.unionAll(risen).groupBy("vid").agg(F.max("status").alias("status")), "state").df


def update(state: DataFrame, compiled: Compiled, facts: DataFrame, options: propagate.RunOptions | None = None) -> DataFrame:
    """State after new facts (vid, kind): equal to a fresh run on all facts."""
    return _raise(state, seed_state(compiled.vertices, facts), compiled, options)


def append(state: DataFrame, compiled: Compiled, new_prop: DataFrame, options: propagate.RunOptions | None = None) -> DataFrame:
    """State after compiled edges were added; compiled holds old and new edges."""
    from supplyrisk.functions.rules import passed

    sent = new_prop.join(state.select(F.col("vid").alias("src"), "status"), "src").select(F.col("dst").alias("vid"), passed(F.col("status"), F.col("mask")).alias("status")).where("status > 0")
    return _raise(state, sent, compiled, options)


def retract(state: DataFrame, compiled: Compiled, removed: DataFrame, left: DataFrame, options: propagate.RunOptions | None = None) -> DataFrame:
    """State after facts were withdrawn. removed: vid of their vertices; left: facts that stay.

    What the withdrawn facts could reach (one frontier for all of them) is reset, then derived
    again from facts inside it and from edges that enter it (delete and rederive). A graph
    that one task may finish is solved again from what stays instead."""
    from supplyrisk.functions.rules import passed

    options = options or propagate.RunOptions()
    n = compiled.n_edges if compiled.n_edges is not None else compiled.prop.count()
    stays = replace(compiled.with_seeds(left), n_edges=n)
    if n <= options.local_cap:
        return propagate.run(stays, "finisher", options)[0]
    # The greatest level passes every edge, so its reach is what any fact could have reached.
    start = removed.select("vid", F.lit(2).alias("status")).distinct()
    hit = Staged(propagate.run(replace(compiled, seeds=start, n_edges=n), "semi_naive", options)[0].select("vid"), "retract").df
    outside = Staged(state.join(hit, "vid", "left_anti"), "retract").df
    border = compiled.prop.join(hit.withColumnRenamed("vid", "dst"), "dst", "left_semi").join(outside.select(F.col("vid").alias("src"), "status"), "src")
    entering = border.select(F.col("dst").alias("vid"), passed(F.col("status"), F.col("mask")).alias("status")).where("status > 0")
    facts = stays.seeds.join(hit, "vid", "left_semi")
    return _raise(outside, facts.unionAll(entering), compiled, options)
