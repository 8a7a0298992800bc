"""What the calculus is compared with."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from supplyrisk.operators import propagate, walks
from supplyrisk.operators.graph import BuildHistory
from supplyrisk.plans.compile import Compiled, compile_graph


def parts_only(graph: BuildHistory, seeds: DataFrame, mode: str = "auto") -> DataFrame:
    """Composition analysis: flagged if any built-in part is, however deep; tools,
    environments and hosts are not looked at."""
    return propagate.run(compile_graph(graph, seeds, "parts_only"), mode)[0]


def flat_inventory(graph: BuildHistory, seeds: DataFrame, mode: str = "auto") -> DataFrame:
    """Every contributor counts, whatever its role."""
    return propagate.run(compile_graph(graph, seeds, "max_impact"), mode)[0]


def attack_tree(compiled: Compiled, target: int, max_depth: int) -> DataFrame:
    """node, parent, depth, gate, leaf of the tree whose goal is a malicious target.

    Every gate is OR (one malicious contributor suffices), so each leaf fact is a minimal
    cut set. Every contributor of every node nearer than max_depth is there, once for each
    parent, at its least depth; the goal has no parent."""
    spark = compiled.prop.sparkSession
    start = spark.createDataFrame([(target,)], "start long")
    nodes = walks.reach(compiled.prop, start, "backward", 2, max_depth).select("vid", F.col("hops").alias("depth"))
    facts = compiled.seeds.where("status = 2").select(F.col("vid").alias("node"), F.lit(True).alias("leaf"))
    edges = compiled.prop.select("src", "dst").distinct()
    a, b = nodes.select(F.col("vid").alias("src"), F.col("depth").alias("far")), nodes.select(F.col("vid").alias("dst"), F.col("depth").alias("near"))
    inner = edges.join(a, "src").join(b, "dst").where(F.col("near") < max_depth).select(F.col("src").alias("node"), F.col("dst").alias("parent"), F.col("far").cast("int").alias("depth"))
    root = spark.createDataFrame([(target, None, 0)], "node long, parent long, depth int")
    return root.unionAll(inner).join(facts, "node", "left").select("node", "parent", "depth", F.lit("OR").alias("gate"), F.coalesce("leaf", F.lit(False)).alias("leaf"))


def sql_recursive(compiled: Compiled, max_depth: int = 60) -> DataFrame:
    """vid, status by Spark's recursive SQL: every path is walked (UNION ALL), so only for
    small acyclic graphs; Spark stops at 100 levels or a million rows."""
    spark = compiled.prop.sparkSession
    compiled.prop.select("src", "dst", "mask").createOrReplaceTempView("_recursive_prop")
    compiled.seeds.createOrReplaceTempView("_recursive_seeds")
    return spark.sql(f"""
        WITH RECURSIVE hit(vid, status, depth) AS (
          SELECT vid, status, 0 FROM _recursive_seeds
          UNION ALL
          SELECT p.dst, h.status, h.depth + 1 FROM hit h JOIN _recursive_prop p ON p.src = h.vid
          WHERE h.depth < {max_depth} AND (h.status = 2 AND p.mask & 2 <> 0 OR h.status = 1 AND p.mask & 1 <> 0))
        SELECT vid, max(status) AS status FROM hit GROUP BY vid""")


def recursive_eval(vertices: Iterable[tuple], edges: Iterable[tuple], seeds: Iterable[tuple], target: int, context: int | None = None) -> tuple[int, frozenset, frozenset, frozenset, frozenset]:
    """Status and sets of one vertex by direct descent through its parents, role by role.

    vertices: (vid, type, identity); edges: (label, src, dst); seeds: (kind, vid). No
    sharing between calls, so only for tiny acyclic graphs: the check of everything else."""
    kind = {v: t for v, t, _ in vertices}
    identity = {v: a for v, _, a in vertices}
    into: dict[int, list[tuple[str, int]]] = {}
    for label, s, d in edges:
        into.setdefault(d, []).append((label, s))
    facts = set(seeds)
    nothing = (0, frozenset(), frozenset(), frozenset(), frozenset())

    def joined(status: int, *verdicts: tuple) -> tuple:
        return (status, *(frozenset().union(*(v[i] for v in verdicts)) for i in range(1, 5)))

    def all_of(parents: list[int], child: int | None) -> tuple:
        got = [one(p, child) for p in parents]
        return joined(max([0, *(g[0] for g in got)]), nothing, *got)

    def one(v: int, child: int | None) -> tuple:
        if v not in kind:
            return joined(2, nothing)
        incoming = into.get(v, [])
        if kind[v] == "artifact":
            got = all_of([p for label, p in incoming], v)
            status = max(2 * (("SM", v) in facts), 1 * (("SV", v) in facts), got[0])
            me = frozenset([v])
            return joined(status, got, (0, me if status == 1 else frozenset(), me if status == 2 else frozenset(), frozenset(), frozenset()))
        if kind[v] == "step":
            tools = all_of([p for label, p in incoming if label == "tools"], None)
            rest = all_of([p for label, p in incoming if label != "tools"], None)
            return joined(max(2 if tools[0] == 2 else 0, rest[0]), tools, rest)
        if kind[v] == "env":
            got = all_of([p for _, p in incoming], None)
            return joined(2 if got[0] == 2 else 0, got)
        present = all_of([p for label, p in incoming if label == "present_in"], None)
        raw = max(present[0], 2 if ("HM", v) in facts else 1 if ("HV", v) in facts else 0)
        weak, status = frozenset([v]) if raw == 1 else frozenset(), 2 if raw == 2 else 0
        got = present
        if child is not None and identity.get(child) is not None:
            copies = all_of([p for label, p in incoming if label in ("published_to", "present_in") and p != child and identity.get(p) == identity[child]], child)
            got = joined(0, got, copies)
            status = max(status, copies[0])
        return joined(status, got, (0, frozenset(), frozenset(), weak, frozenset([v]) if status == 2 else frozenset()))

    return one(target, context)
