"""Folding the role rules into masked propagation edges.

A compiled graph is `prop(src, dst, mask, label)`, a seed state and the copy edges of the
storage-host rule. Status is then the greatest level that any path hands on, whatever the
type of its vertices, and both levels are plain reachability problems.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from supplyrisk.functions.rules import PASS, TRANSFER, transfer_table
from supplyrisk.operators import blocks, kernels
from supplyrisk.operators.graph import BuildHistory
from supplyrisk.plans.staging import Staged, partitions, stage

LEVEL_OF_KIND = {"SV": 1, "SM": 2, "HV": 1, "HM": 2}
#: Edges (24 bytes each) up to which one task may finish a graph.
LOCAL_CAP = 4_000_000
LABELS = (*dict.fromkeys(label for label, _ in TRANSFER),)
PARTS_ONLY = {("feeds", "step"), ("produces", "artifact"), ("copy", "artifact")}


@dataclass
class Compiled:
    """prop: src, dst, mask, label. seeds: vid, status. copies: host, akey, vid, side, from which
    copy edges are made. unknown: vids that edges start at but no vertex has."""

    vertices: DataFrame
    prop: DataFrame
    seeds: DataFrame
    copies: DataFrame
    unknown: DataFrame
    n_edges: int | None = None
    buckets: int | None = None
    #: One row with the laid-out edges, if there are at most LOCAL_CAP; masks by label for it.
    packed: DataFrame | None = None
    masks: tuple[int, ...] | None = None
    #: The edges laid out by blocks, if there are more than LOCAL_CAP; masks by label hold for it too.
    blocks: blocks.Blocks | None = None
    #: What of a vertex id its block follows from; None: all of it.
    home: Callable[[Column], Column] | None = None
    #: Vertices among which are all without out-edges; None: all of them.
    ends: DataFrame | None = None
    #: Whether vertices that edges start at but that do not exist are malicious.
    unknown_is_malicious: bool = False

    def staged(self, made: bool = False) -> Compiled:
        """Edges computed once and counted; laid out for single tasks if they are few, else by blocks.
        made: they are a table already."""
        df = self.prop if made else stage(self.prop, "prop")
        n = df.count()
        packed = Staged(kernels.packed_graph(df, LABELS), "packed", "none").df if n <= LOCAL_CAP else None
        laid = blocks.lay_out(df, self.ends if self.ends is not None else self.vertices, LABELS, n, self.home) if packed is None else None
        return replace(self, prop=df, n_edges=n, packed=packed, blocks=laid, masks=None, unknown=stage(self.unknown, "unknown"))

    def in_blocks(self) -> Compiled:
        """Laid out by blocks, whatever the size."""
        if self.blocks is not None:
            return self
        n = self.n_edges if self.n_edges is not None else self.prop.count()
        return replace(self, n_edges=n, blocks=blocks.lay_out(self.prop, self.ends if self.ends is not None else self.vertices, LABELS, n, self.home), masks=None)

    def variant(self, rules: str = "paper", drop_labels: tuple[str, ...] = ()) -> Compiled:
        """Another rule set on the same edges: masks follow from labels, nothing is compiled again.

        This one must hold the paper's rules; n_edges stays as an upper bound."""
        masks = [0 if label in drop_labels else PASS if rules == "max_impact" else -1 for label in LABELS]
        if rules == "parts_only":
            kept = {label for label, _ in PARTS_ONLY}
            masks = [PASS if label in kept and label not in drop_labels else 0 for label in LABELS]
        of = F.get(F.array(*[F.lit(m) for m in masks]), (F.array_position(F.array(*[F.lit(x) for x in LABELS]), F.col("label")) - 1).cast("int"))
        new = F.when(of >= 0, of).otherwise(F.col("mask")).cast(self.prop.schema["mask"].dataType)
        prop = self.prop.withColumn("mask", new).where("mask <> 0")
        return replace(self, prop=prop, buckets=None, masks=tuple(masks))

    def laid_out(self, buckets: int | None = None) -> Compiled:
        """Edges staged once, in folders by mask and bucket of src, sorted by src: a level-1
        frontier reads only edges that pass it, a small one only its sources' buckets."""
        spark = self.prop.sparkSession
        n = buckets or partitions(spark)
        prop = self.prop.withColumn("bucket", F.pmod(F.xxhash64("src"), F.lit(n)).cast("int"))
        staged = Staged(prop.repartition(n, "bucket").sortWithinPartitions("mask", "bucket", "src"), "prop", by=("mask", "bucket"))
        return replace(self, prop=staged.df, n_edges=staged.df.count(), buckets=n)

    def with_seeds(self, seeds: DataFrame, host_vuln: str = "record") -> Compiled:
        state = seed_state(self.vertices, seeds, host_vuln)
        if self.unknown_is_malicious:
            state = state.unionAll(self.unknown.select("vid", F.lit(2).alias("status")))
        return replace(self, seeds=state)


def seed_state(vertices: DataFrame, seeds: DataFrame, host_vuln: str = "record") -> DataFrame:
    """vid, status of known facts, at most one row each. host_vuln: record or ignore HV facts.

    Facts about unknown vertices, or of a kind that does not fit the type, are left out."""
    level = F.when(F.col("kind").isin("SM", "HM"), 2).when(F.col("kind").isin("SV", "HV"), 1)
    used = seeds.where(F.col("kind") != "HV") if host_vuln == "ignore" else seeds
    facts = used.select("vid", "kind", level.alias("level")).where("level is not null")
    kinds = vertices.select("vid", "vtype")
    fits = F.when(F.col("kind").isin("SV", "SM"), F.col("vtype") == "artifact").otherwise(F.col("vtype") == "host")
    return facts.join(kinds, "vid").where(fits).groupBy("vid").agg(F.max("level").cast("int").alias("status"))


def copy_sides(graph: BuildHistory) -> DataFrame:
    """host, akey, vid, side: artifacts with an identity that a host holds (`held`) and that
    are fetched from it (`fetched`). What a fetched artifact may take its status from is
    held under its identity at its host, itself excepted."""
    names = graph.vertices.where("vtype = 'artifact' and akey is not null").select("vid", "akey")
    hosts = graph.vertices.where("vtype = 'host'").select(F.col("vid").alias("host"))
    fetched = graph.edges.where("label = 'fetched_from'").select(F.col("src").alias("host"), F.col("dst").alias("vid"), F.lit("fetched").alias("side"))
    held = graph.edges.where(F.col("label").isin("published_to", "present_in")).select(F.col("dst").alias("host"), F.col("src").alias("vid"), F.lit("held").alias("side"))
    both = fetched.unionAll(held.join(hosts, "host", "left_semi")).distinct()
    return both.join(names, "vid").select("host", "akey", "vid", "side")


def copy_edges(sides: DataFrame, predecessor_only: bool = False) -> DataFrame:
    """src, dst: a fetched artifact takes the status of the copies with its identity that the
    host holds. Joined on (host, identity), so a busy host is not one key; where several
    are held and several fetched, they meet in a hub (a vertex of its own, negative id), so
    edges are linear in the copies. predecessor_only: only copies of smaller ids, by pairs."""
    group = ["host", "akey"]
    fetched = sides.where("side = 'fetched'").select(*group, F.col("vid").alias("dst"))
    held = sides.where("side = 'held'").select(*group, F.col("vid").alias("src"))
    if predecessor_only:
        return fetched.join(held, group).where("src < dst").select("src", "dst")
    sizes = sides.groupBy(*group).agg(F.count_if(F.col("side") == "held").alias("h"), F.count_if(F.col("side") == "fetched").alias("f"))
    many = Staged(sizes.where("h * f > h + f").select(*group, (-1 - F.monotonically_increasing_id()).alias("hub")), "hubs").df
    if not many.limit(1).count():
        return fetched.join(held, group).where("src <> dst").select("src", "dst")
    few = fetched.join(many, group, "left_anti").join(held, group).where("src <> dst").select("src", "dst")
    into = held.join(many, group).select("src", F.col("hub").alias("dst"))
    return few.unionAll(into).unionAll(fetched.join(many, group).select(F.col("hub").alias("src"), "dst"))


def compile_graph(graph: BuildHistory, seeds: DataFrame | None = None, rules: str = "paper", drop_labels: tuple[str, ...] = (), unknown: str = "malicious", predecessor_only: bool = False, host_vuln: str = "record") -> Compiled:
    """rules: paper, max_impact (roles ignored) or parts_only (composition alone).

    unknown: what an edge from no known vertex does: malicious, ignore or error."""
    spark = graph.vertices.sparkSession
    kinds = graph.vertices.select(F.col("vid").alias("dst"), F.col("vtype").alias("dst_type"))
    table = transfer_table(spark, rules)
    copies = copy_sides(graph)
    edges = graph.edges.where(~F.col("label").isin("published_to", *drop_labels)).select("src", "dst", "label").join(kinds, "dst")
    if "copy" not in drop_labels:
        met = copy_edges(copies, predecessor_only)
        edges = edges.select("src", "dst", "label", "dst_type").unionAll(met.select("src", "dst", F.lit("copy").alias("label"), F.lit("artifact").alias("dst_type")))
    if rules == "parts_only":
        table = spark.createDataFrame([(label, kind, PASS) for label, kind in TRANSFER if (label, kind) in PARTS_ONLY], "label string, dst_type string, mask int")
    prop = edges.join(F.broadcast(table), ["label", "dst_type"]).select("src", "dst", "mask", "label").distinct()

    missing = graph.edges.where("label <> 'published_to'").select(F.col("src").alias("vid")).distinct().join(graph.vertices.select("vid"), "vid", "left_anti")
    if unknown == "error" and missing.limit(1).count():
        raise ValueError("edges start at vertices that do not exist")
    state = seed_state(graph.vertices, seeds, host_vuln) if seeds is not None else None
    if state is None:
        state = spark.createDataFrame([], "vid long, status int")
    if unknown == "malicious":
        state = state.unionAll(missing.select("vid", F.lit(2).alias("status")))
    return Compiled(graph.vertices, prop, state, copies, missing, unknown_is_malicious=unknown == "malicious")


def contract_steps(compiled: Compiled, keep: DataFrame | None = None) -> tuple[Compiled, DataFrame]:
    """Vertices with one in-edge and no fact, taken out: their out-edges start at their parent
    with the masks' common bits. Returns the smaller graph and restore(vid, parent, mask).

    Only vertices whose parent stays are taken, so one pass suffices; keep: vids to spare."""
    prop = compiled.prop.select("src", "dst", "mask").distinct()
    single = prop.groupBy("dst").agg(F.count("*").alias("n"), F.min("src").alias("parent"), F.min("mask").alias("mask")).where("n = 1 and parent <> dst").drop("n")
    single = single.join(compiled.seeds.select(F.col("vid").alias("dst")), "dst", "left_anti")
    if keep is not None:
        single = single.join(keep.select(F.col("vid").alias("dst")), "dst", "left_anti")
    # Of a chain of such vertices every second one at most goes: those whose parent is not one.
    gone = single.join(single.select(F.col("dst").alias("parent")), "parent", "left_anti").select(F.col("dst").alias("vid"), "parent", "mask")
    kept = prop.join(gone.select(F.col("vid").alias("dst")), "dst", "left_anti")
    moved = kept.join(gone.select(F.col("vid").alias("src"), "parent", F.col("mask").alias("first")), "src", "left")
    new = moved.select(F.coalesce("parent", "src").alias("src"), "dst", F.when(F.col("first").isNull(), F.col("mask")).otherwise(F.col("mask").bitwiseAND(F.col("first"))).alias("mask"), F.lit("path").alias("label"))
    return replace(compiled, prop=new.where("mask <> 0").distinct(), n_edges=None, buckets=None, packed=None, masks=None, blocks=None), gone
