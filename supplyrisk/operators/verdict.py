"""Verdicts: status and the four sets behind chosen targets."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from supplyrisk.functions.lattice import SETS, max_status, merge
from supplyrisk.operators import propagate, walks
from supplyrisk.plans.compile import Compiled
from supplyrisk.plans.staging import Staged

CLASSES = ("SV", "SM", "HV", "HM")


def contexts(compiled: Compiled, state: DataFrame) -> DataFrame:
    """host, artifact, context_status of each fetched artifact that has copies at its host.

    An uncompromised host takes the greatest status of those copies for this artifact's
    chain only; a compromised one is 2 for every chain."""
    known = compiled.copies.join(state, "vid", "left").select("host", "akey", "vid", "side", F.coalesce("status", F.lit(0)).alias("status"))
    held = known.where("side = 'held'")
    levels = held.groupBy("host", "akey").agg(*[F.count_if(F.col("status") == k).alias(f"n{k}") for k in (0, 1, 2)])
    own = held.select("host", "akey", "vid", F.col("status").alias("own"))
    fetched = known.where("side = 'fetched'").select("host", "akey", "vid").join(levels, ["host", "akey"]).join(own, ["host", "akey", "vid"], "left")
    # Itself is no copy: it is taken off the count of its level.
    others = [F.col(f"n{k}") - F.coalesce((F.col("own") == k).cast("int"), F.lit(0)) for k in (0, 1, 2)]
    copy_status = F.when(others[2] > 0, 2).when(others[1] > 0, 1).when(others[0] > 0, 0)
    worst = fetched.select("host", F.col("vid").alias("artifact"), copy_status.alias("copy_status")).where("copy_status is not null")
    raw = state.select(F.col("vid").alias("host"), F.col("status").alias("raw"))
    status = F.when(F.col("raw") == 2, 2).otherwise(F.col("copy_status"))
    return worst.join(raw, "host", "left").select("host", "artifact", status.alias("context_status"))


def tainted_distribution(compiled: Compiled, state: DataFrame) -> DataFrame:
    """host, artifact: hosts compromised for the chain of one artifact, not of themselves."""
    raw = state.where("status = 2").select(F.col("vid").alias("host"))
    return contexts(compiled, state).where("context_status = 2").join(raw, "host", "left_anti").select("host", "artifact")


def verdict_members(compiled: Compiled, targets: DataFrame, state: DataFrame | None = None, options: propagate.RunOptions | None = None) -> DataFrame:
    """target, cls (SV, SM, HV, HM), vid: the long form, distinct rows.

    targets: column `target`, vertices of any type. Members are those of the compiled
    ancestors, target included; unknown vertices are in no set."""
    start = targets.select(F.col("target").alias("start"))
    if (compiled.n_edges or 0) > (options or propagate.RunOptions()).local_cap and compiled.buckets is None:
        from supplyrisk.operators.exposure import ancestors

        pairs = Staged(ancestors(compiled, start, options), "ancestors").df
    else:
        pairs = Staged(walks.reach(compiled.prop, start, "backward", 3, options=options), "ancestors").df
    if state is None:
        # The ancestors hold all that can reach the targets, so the induced edges suffice.
        inside = pairs.select("vid").distinct()
        prop = compiled.prop.join(inside.withColumnRenamed("vid", "src"), "src", "left_semi").join(inside.withColumnRenamed("vid", "dst"), "dst", "left_semi")
        small = Compiled(compiled.vertices, prop, compiled.seeds.join(inside, "vid", "left_semi"), compiled.copies, compiled.unknown)
        state, _ = propagate.run(small, "auto", options)
    flagged = compiled.vertices.select("vid", "vtype").where(F.col("vtype").isin("artifact", "host")).join(state, "vid")
    cls = F.when(F.col("vtype") == "artifact", F.when(F.col("status") == 2, "SM").otherwise("SV")).otherwise(F.when(F.col("status") == 2, "HM").otherwise("HV"))
    own = pairs.select(F.col("start").alias("target"), "vid").join(flagged.select("vid", cls.alias("cls")), "vid").select("target", "cls", "vid")
    # A host that hands a malicious copy to a visited artifact.
    handed = tainted_distribution(compiled, state)
    fetched = pairs.select(F.col("start").alias("target"), F.col("vid").alias("artifact")).join(handed, "artifact").select("target", F.lit("HM").alias("cls"), F.col("host").alias("vid"))
    return own.unionAll(fetched).distinct()


def verdict(compiled: Compiled, targets: DataFrame, state: DataFrame | None = None, initial: DataFrame | None = None, disjoint_sets: bool = False, context: DataFrame | None = None, options: propagate.RunOptions | None = None) -> DataFrame:
    """target, status, sv, sm, hv, hm (sorted arrays): one row per target.

    initial: a wide verdict (columns as the result's, no target) merged into each.
    context: host, artifact: the status of a host target is then that of the chain that
    fetches the artifact. disjoint_sets: a host in hm is not listed in hv."""
    if state is None:
        state, _ = propagate.run(compiled, "auto", options)
    members = Staged(verdict_members(compiled, targets, state, options), "members").df
    grouped = members.groupBy("target").agg(*[F.array_sort(F.collect_set(F.when(F.col("cls") == c, F.col("vid")))).alias(s) for c, s in zip(CLASSES, SETS, strict=True)])
    unknown = compiled.unknown.select(F.col("vid").alias("target"), F.lit(2).alias("unknown"))
    out = targets.select("target").distinct().join(state.select(F.col("vid").alias("target"), "status"), "target", "left").join(unknown, "target", "left").join(grouped, "target", "left")
    empty = F.array().cast("array<long>")
    out = out.select("target", F.coalesce("unknown", "status", F.lit(0)).alias("status"), *[F.coalesce(s, empty).alias(s) for s in SETS])
    if context is not None:
        chain = contexts(compiled, state).join(context.select("host", "artifact"), ["host", "artifact"], "left_semi").groupBy(F.col("host").alias("target")).agg(F.max("context_status").alias("chain"))
        out = out.join(chain, "target", "left").withColumn("status", F.greatest("status", F.coalesce("chain", F.lit(0)))).drop("chain")
    if initial is not None:
        start = F.broadcast(initial.select(F.struct("status", *SETS).alias("initial")).limit(1))
        both = merge(max_status(F.col("status"), F.col("initial.status")), F.struct(*SETS), F.col("initial"))
        out = out.crossJoin(start).select("target", both.alias("v")).select("target", "v.*")
    if disjoint_sets:
        out = out.withColumn("hv", F.array_except("hv", "hm"))
    return out


def verdict_counts(verdicts: DataFrame) -> DataFrame:
    return verdicts.select("target", "status", *[F.size(s).alias(f"n_{s}") for s in SETS])


def verdict_union(verdicts: DataFrame) -> DataFrame:
    """One row: greatest status and the union of each set over all verdicts.

    Members are made distinct in the long form first, so only what the answer holds meets."""
    cls = F.explode(F.array(*[F.struct(F.lit(s).alias("cls"), F.col(s).alias("vids")) for s in SETS])).alias("x")
    members = verdicts.select(cls).select("x.cls", F.explode("x.vids").alias("vid")).distinct()
    sets = members.agg(*[F.array_sort(F.collect_set(F.when(F.col("cls") == s, F.col("vid")))).alias(s) for s in SETS])
    return verdicts.agg(F.max("status").alias("status")).crossJoin(F.broadcast(sets))  # one row each


def verdict_sizes(compiled: Compiled, state: DataFrame, options: propagate.RunOptions | None = None, lg_k: int = 12, targets: DataFrame | None = None) -> DataFrame:
    """vid, n_sv, n_sm, n_hv, n_hm estimates for all vertices (or targets) at once.

    Each vertex carries one sketch per class; a round unites what its parents know. The
    sets themselves, quadratic in the graph, are never made."""
    options = options or propagate.RunOptions()
    edges = Staged(compiled.prop.select("src", "dst").distinct(), "sizes-edges").df
    flagged = compiled.vertices.select("vid", "vtype").join(state, "vid").where(F.col("vtype").isin("artifact", "host"))
    cls = F.concat(F.when(F.col("vtype") == "artifact", "S").otherwise("H"), F.when(F.col("status") == 2, "M").otherwise("V"))
    own = flagged.select("vid", cls.alias("cls"), F.col("vid").alias("member"))
    handed = tainted_distribution(compiled, state).select(F.col("artifact").alias("vid"), F.lit("HM").alias("cls"), F.col("host").alias("member"))
    known = Staged(own.unionAll(handed).groupBy("vid", "cls").agg(F.hll_sketch_agg("member", lg_k).alias("sketch")), "sizes").df
    size = known.select("vid", "cls", F.hll_sketch_estimate("sketch").alias("n"))
    for _ in range(options.max_rounds):
        sent = known.join(edges.withColumnRenamed("src", "vid"), "vid").select(F.col("dst").alias("vid"), "cls", "sketch")
        new = Staged(known.unionAll(sent).groupBy("vid", "cls").agg(F.hll_union_agg("sketch").alias("sketch")), "sizes").df
        # Estimates only grow; a round that changes none is the last.
        new_size = Staged(new.select("vid", "cls", F.hll_sketch_estimate("sketch").alias("n")), "sizes").df
        changed = new_size.exceptAll(size).limit(1).count()
        known, size = new, new_size
        if not changed:
            break
    wide = size.groupBy("vid").agg(*[F.coalesce(F.max(F.when(F.col("cls") == c, F.col("n"))), F.lit(0)).alias(f"n_{s}") for c, s in zip(CLASSES, SETS, strict=True)])
    return wide if targets is None else wide.join(targets.select(F.col("target").alias("vid")), "vid", "left_semi")


def explain(compiled: Compiled, state: DataFrame, target: int, k: int = 1, options: propagate.RunOptions | None = None) -> DataFrame:
    """target, rank, hop, vid, label: a shortest path from each of the k facts nearest to the
    target that explain its status (rank 1 is the nearest, ties by smaller id; hop 0 is the
    target; label is of the edge into the vertex, null for the fact).

    Each vertex keeps its parent of fewest hops, then smallest id. Only what k paths cross
    comes to the driver."""
    options = options or propagate.RunOptions()
    spark = compiled.prop.sparkSession
    schema = "target long, rank int, hop int, vid long, label string"
    level = state.where(F.col("vid") == target).select("status").first()
    if level is None:
        return spark.createDataFrame([], schema)
    need = 2 if level[0] == 2 else 1
    edges = Staged(compiled.prop.where(F.col("mask").bitwiseAND(F.lit(need)) != 0).select("src", "dst", "label"), "explain").df
    facts = compiled.seeds.where(F.col("status") == level[0]).select("vid")
    # Backward from the target, a layer per hop, until enough facts are met.
    layers = [Staged(spark.createDataFrame([(target, None, None)], "vid long, child long, label string"), "explain").df]
    seen, found = layers[0].select("vid"), []
    while True:
        met = layers[-1].join(facts, "vid", "left_semi").orderBy("vid").limit(k - len(found)).collect()
        found += [(len(layers) - 1, row["vid"]) for row in met]
        if len(found) == k or len(layers) > options.max_rounds:
            break
        step = layers[-1].select(F.col("vid").alias("dst")).join(edges, "dst").groupBy(F.col("src").alias("vid")).agg(F.min(F.struct("dst", "label")).alias("m"))
        step = step.join(seen, "vid", "left_anti").select("vid", F.col("m.dst").alias("child"), F.col("m.label").alias("label"))
        layer = Staged(step, "explain").df
        if not layer.limit(1).count():
            break
        layers.append(layer)
        seen = seen.unionAll(layer.select("vid"))
        if len(layers) % options.compact_every == 0:
            seen = Staged(seen, "explain").df
    # Forward again: a layer is read once, for the at most k vertices that paths cross in it.
    rows, at, into = [], {}, {}
    for hop in range(len(layers) - 1, -1, -1):
        at |= {rank: vid for rank, (far, vid) in enumerate(found, 1) if far == hop}
        if not at:
            continue
        kept = {row["vid"]: row for row in layers[hop].where(F.col("vid").isin(sorted(set(at.values())))).collect()}
        for rank, vid in at.items():
            rows.append((target, rank, hop, vid, into.get(rank)))
            at[rank], into[rank] = kept[vid]["child"], kept[vid]["label"]
    return spark.createDataFrame(rows, schema)
