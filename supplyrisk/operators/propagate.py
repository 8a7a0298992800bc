"""Whole-graph status: the least fixpoint of the compiled rules.

`semi_naive` sends only raised vertices over their out-edges each round; `two_phase`
settles malice first, then vulnerability around it; `contracted` takes out pass-through
vertices before; `jumping` folds linear stretches by pointer jumping; `levels` goes by topological rank; `finisher` solves a graph of checked
size in one task; `auto` counts the edges and picks the last where it fits. A larger graph is laid out by blocks
and finished by numbers in one task (operators/gathered.py), beyond its cap block by block (operators/blocks.py),
by the loop of joins if it was laid out in folders. All give the same statuses.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field, replace
from functools import partial

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from supplyrisk.functions.rules import passed
from supplyrisk.operators import blocks, gathered, kernels
from supplyrisk.plans.compile import LABELS, LOCAL_CAP, Compiled, contract_steps
from supplyrisk.plans.staging import Staged


@dataclass
class RunOptions:
    """max_rounds: rounds after which a loop gives up. compact_every: rounds after which the
    state is rewritten. broadcast_rows: frontier rows (16 bytes each) up to which the edges
    are not shuffled. local_cap: edges (24 bytes each) up to which one task may finish; gather_cap:
    edges laid out by blocks up to which one task may finish by numbers (13 bytes each)."""

    max_rounds: int = 10_000
    compact_every: int = 8
    broadcast_rows: int = 200_000
    local_cap: int = LOCAL_CAP
    gather_cap: int = gathered.GATHER_CAP


@dataclass
class RunLog:
    mode: str = ""
    rounds: list[dict] = field(default_factory=list)

    def add(self, **row: object) -> None:
        self.rounds.append(row)

    def frame(self, spark) -> DataFrame:
        rows = [(self.mode, i, r.get("frontier", 0), r.get("messages", 0), r.get("raised", 0), r.get("shuffle_bytes", 0), float(r.get("seconds", 0))) for i, r in enumerate(self.rounds)]
        return spark.createDataFrame(rows, "mode string, round int, frontier long, messages long, raised long, shuffle_bytes long, seconds double")


def shuffled_bytes(spark) -> int:
    """Bytes that all executors have written for shuffles so far."""
    executors = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    return sum(executors.apply(i).totalShuffleWrite() for i in range(executors.size()))


def _edges_from(prop: DataFrame, frontier: DataFrame, n: int, options: RunOptions, low_only: bool, buckets: int | None) -> DataFrame:
    """Edges that leave the frontier. Laid-out edges are pruned by mask, and by bucket (of
    `buckets`) if the frontier is small."""
    if low_only:
        prop = prop.where("mask = 3")
    small = n <= options.broadcast_rows
    if buckets and n <= buckets // 2:
        ids = [r[0] for r in frontier.select(F.pmod(F.xxhash64("vid"), F.lit(buckets)).cast("int").alias("b")).distinct().collect()]
        prop = prop.where(F.col("bucket").isin(ids))
    from_ = frontier.select(F.col("vid").alias("src"), F.col("status").alias("level"))
    return prop.join(F.broadcast(from_) if small else from_, "src")


def _loop(prop: DataFrame, start: DataFrame, options: RunOptions, log: RunLog, mode: str = "both", settled: DataFrame | None = None, buckets: int | None = None) -> DataFrame:
    """vid, status raised from the start. mode: both levels, or `top` or `low` alone.
    settled: vids that take no part."""
    staged = [Staged(start.groupBy("vid").agg(F.max("status").alias("status")), "state")]
    frontier, state = staged[0].df, staged[0].df
    n = frontier.count()
    history = [state]
    for round_ in range(options.max_rounds):
        if not n:
            return state
        began, written, seen = time.time(), shuffled_bytes(prop.sparkSession), Observation()
        low_only = mode == "low"
        sent = _edges_from(prop, frontier, n, options, low_only, buckets)
        got = sent.select(F.col("dst").alias("vid"), passed(F.col("level"), F.col("mask")).alias("status")).where("status > 0").groupBy("vid").agg(F.max("status").alias("status"), F.count("*").alias("m"))
        got = got.observe(seen, F.coalesce(F.sum("m"), F.lit(0)).alias("messages")).drop("m")
        old = state.select("vid", F.col("status").alias("old"))
        raised = got.join(old, "vid", "left").where("status > coalesce(old, 0)").select("vid", "status")
        if settled is not None:
            raised = raised.join(settled.select("vid"), "vid", "left_anti")
        grown = Observation()
        step = Staged(raised.observe(grown, F.count(F.lit(1)).alias("n")), "frontier")
        sent_from, frontier = n, step.df
        n = grown.get["n"]
        log.add(frontier=sent_from, messages=seen.get.get("messages", 0), raised=n, shuffle_bytes=shuffled_bytes(prop.sparkSession) - written, seconds=time.time() - began)
        history.append(frontier)
        staged.append(step)
        union = history[0]
        for h in history[1:]:
            union = union.unionAll(h)
        state = union.groupBy("vid").agg(F.max("status").alias("status"))
        if len(history) > options.compact_every:
            whole = Staged(state, "state")
            for s in staged[:-1]:
                s.drop()
            staged, state, history = [whole, step], whole.df, [whole.df]
    raise RuntimeError(f"no fixpoint after {options.max_rounds} rounds")


def _by_levels(compiled: Compiled, options: RunOptions, log: RunLog) -> DataFrame:
    """One round per topological rank; vertices on or behind cycles are left to the loop."""
    from supplyrisk.operators.walks import topo_levels

    ranked = Staged(topo_levels(compiled.prop, compiled.vertices, options), "levels").df
    top = ranked.agg(F.max("level")).first()[0]
    rank = ranked.where("level is not null")
    edges = Staged(compiled.prop.select("src", "dst", "mask").join(rank.select(F.col("vid").alias("dst"), "level"), "dst"), "by-level", by=("level",)).df
    state = compiled.seeds.groupBy("vid").agg(F.max("status").alias("status"))
    done = Staged(state, "state").df
    for level in range(1, (top or 0) + 1):
        from_ = done.select(F.col("vid").alias("src"), F.col("status").alias("s"))
        got = edges.where(F.col("level") == level).join(from_, "src").select(F.col("dst").alias("vid"), passed(F.col("s"), F.col("mask")).alias("status")).where("status > 0")
        done = Staged(done.unionAll(got).groupBy("vid").agg(F.max("status").alias("status")), "state").df
        log.add(frontier=level)
    return _loop(compiled.prop, done, options, log)


def run(compiled: Compiled, mode: str = "auto", options: RunOptions | None = None) -> tuple[DataFrame, RunLog]:
    """(vid, status of all that is not safe, log)."""
    options = options or RunOptions()
    log = RunLog(mode)
    if compiled.n_edges is None:
        compiled = replace(compiled, prop=Staged(compiled.prop, "prop").df, packed=None, masks=None, blocks=None)
        compiled = replace(compiled, n_edges=compiled.prop.count())
    far = compiled.n_edges > options.local_cap
    if mode == "auto":
        mode = "semi_naive" if far else "finisher"
        log.mode = f"auto: {mode}"
    if far and (mode == "finisher" or compiled.buckets is None and mode in ("semi_naive", "two_phase")):
        at, seeds = compiled.in_blocks(), compiled.seeds
        if compiled.n_edges <= options.gather_cap:  # malice first in any mode
            began = time.time()
            state = gathered.solve(at.blocks, at.masks, seeds)
            log.add(seconds=time.time() - began)
            return state, log
        solve = partial(blocks.solve, at.blocks, at.masks, max_rounds=options.max_rounds, log=log)
        if mode != "two_phase":
            return solve(seeds), log
        return solve(seeds.where("status = 1"), solve(seeds.where("status = 2"))), log
    if mode == "finisher":
        if compiled.packed is not None:
            packed, masks = compiled.packed, compiled.masks
        else:
            packed, masks = kernels.packed_graph(compiled.prop if "label" in compiled.prop.columns else compiled.prop.withColumn("label", F.lit("")), LABELS), None
        state = kernels.status_in_one_task(packed, compiled.seeds.groupBy("vid").agg(F.max("status").alias("status")), masks)
        return Staged(state, "status").df, log
    if mode == "semi_naive":
        return _loop(compiled.prop, compiled.seeds, options, log, buckets=compiled.buckets), log
    if mode == "two_phase":
        bad = _loop(compiled.prop, compiled.seeds.where("status = 2"), options, log, "top", buckets=compiled.buckets)
        bad = Staged(bad, "malice").df
        weak = compiled.seeds.where("status = 1").join(bad.select("vid"), "vid", "left_anti")
        return bad.unionAll(_loop(compiled.prop, weak, options, log, "low", bad, compiled.buckets)), log
    if mode == "contracted":
        small, gone = contract_steps(compiled)
        gone = Staged(gone, "contracted").df
        state, _ = run(small, "auto", options)
        back = gone.join(state.select(F.col("vid").alias("parent"), "status"), "parent").select("vid", passed(F.col("status"), F.col("mask")).alias("status")).where("status > 0")
        return Staged(state.unionAll(back), "status").df, log
    if mode == "jumping":
        from supplyrisk.operators.jumping import fold_stretches, unfold

        small, folded = fold_stretches(compiled)
        state, _ = run(small, "auto", options)
        return Staged(state.unionAll(unfold(state, folded)), "status").df, log
    if mode == "levels":
        return _by_levels(compiled, options, log), log
    raise ValueError(mode)


def finish(compiled: Compiled, state: DataFrame) -> DataFrame:
    """vid, vtype, status of every vertex; what has no state is safe."""
    return compiled.vertices.select("vid", "vtype").join(state, "vid", "left").select("vid", "vtype", F.coalesce("status", F.lit(0)).alias("status"))
