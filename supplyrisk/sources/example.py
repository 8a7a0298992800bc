"""The worked example: eleven vertices around one build step."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from supplyrisk.operators.graph import BuildHistory
from supplyrisk.sources.schema import EDGES as EDGE_TYPE
from supplyrisk.sources.schema import SEEDS, VERTICES
from supplyrisk.sources.tables import table

#: The example's vertices have numbers below this; an instance's id is instance * SIZE + number.
SIZE = 16

# The example's vertices and edges (two edges complete what only a figure shows).
TYPES = {1: "host", 2: "artifact", 3: "artifact", 4: "artifact", 5: "host", 6: "artifact", 7: "env", 8: "step", 9: "artifact", 10: "artifact", 11: "host"}
EDGES = (
    ("present_in", 4, 5), ("present_in", 3, 7), ("hosts_env", 5, 7), ("runs_step", 7, 8), ("tools", 2, 8), ("feeds", 6, 8),
    ("produces", 8, 9), ("produces", 8, 10), ("published_to", 9, 11), ("published_to", 10, 11), ("fetched_from", 1, 2), ("fetched_from", 1, 6),
)
USE_CASES = {"uc1": [("SV", 2), ("SV", 3), ("SV", 4)], "uc2": [("SV", 6)], "uc3": [("SM", 4)]}


def graph(spark: SparkSession, extra_vertices: dict[int, tuple[str, str | None]] | None = None, extra_edges: tuple = ()) -> BuildHistory:
    """extra_vertices: type and identity by id. extra_edges: (label, src, dst)."""
    kinds = {v: (t, f"A{v}" if t == "artifact" else None) for v, t in TYPES.items()} | (extra_vertices or {})
    vertices = [(v, t, akey, None) for v, (t, akey) in kinds.items()]
    edges = [(i, s, d, label, None) for i, (label, s, d) in enumerate((*EDGES, *extra_edges), 1_000_001)]
    return BuildHistory(spark.createDataFrame(vertices, VERTICES), spark.createDataFrame(edges, EDGE_TYPE))


def seeds(spark: SparkSession, facts: list[tuple[str, int]]) -> DataFrame:
    return spark.createDataFrame([(v, k, None, None, None, None) for k, v in facts], SEEDS)


# --- one instance of the example for each conversation ------------------------------------


def instances(spark: SparkSession, sf_dir: str) -> DataFrame:
    """conv_id, flagged of each conversation: a use case's facts hold where its texts have an odd length in all."""
    odd = F.sum(F.length("text")) % 2 == 1
    return table(spark, sf_dir, "conversations").groupBy("conv_id").agg(F.coalesce(odd, F.lit(False)).alias("flagged"))


def instance_id(number: Column) -> Column:
    return F.col("conv_id") * SIZE + number


def instance_of(vid: Column) -> Column:
    return F.shiftright(vid, 4)


def number_of(vid: Column) -> Column:
    return vid.bitwiseAND(F.lit(SIZE - 1).cast("long"))


def _each(rows: DataFrame, values: list[tuple], names: tuple[str, ...]) -> DataFrame:
    """rows, once for each of the literal values."""
    literal = F.array(*[F.struct(*[F.lit(x).alias(n) for x, n in zip(v, names, strict=True)]) for v in values])
    return rows.select("*", F.inline(literal))


def graph_over(spark: SparkSession, sf_dir: str, misfed: bool = False) -> BuildHistory:
    """The example once for each conversation. misfed: where flagged, the host feeds the step itself."""
    each, no_props = instances(spark, sf_dir), F.lit(None).cast("map<string,string>").alias("props")
    v = _each(each, [(i, kind) for i, kind in TYPES.items()], ("number", "vtype"))
    akey = F.when(F.col("vtype") == "artifact", F.concat(F.lit("A"), F.col("number").cast("string"), F.lit("/"), F.col("conv_id").cast("string")))
    vertices = v.select(instance_id(F.col("number")).alias("vid"), "vtype", akey.alias("akey"), no_props)
    e = _each(each, list(EDGES), ("label", "s", "d"))
    src = F.when(F.lit(misfed) & F.col("flagged") & (F.col("label") == "feeds"), F.lit(1)).otherwise(F.col("s"))
    edges = e.select(instance_id(src).alias("src"), instance_id(F.col("d")).alias("dst"), "label")
    eid = (-1 - F.xxhash64("src", "dst", "label").bitwiseAND(F.lit(2**62 - 1))).alias("eid")
    return BuildHistory(vertices, edges.select(eid, "src", "dst", "label", no_props))


def seeds_over(spark: SparkSession, sf_dir: str, facts: list[tuple[str, int]]) -> DataFrame:
    """vid, kind: the facts in each flagged instance."""
    return _each(instances(spark, sf_dir).where("flagged"), facts, ("kind", "number")).select(instance_id(F.col("number")).cast("long").alias("vid"), "kind")


def targets_over(spark: SparkSession, sf_dir: str) -> DataFrame:
    """target: both products of each instance."""
    return _each(instances(spark, sf_dir), [(9,), (10,)], ("number",)).select(instance_id(F.col("number")).alias("target"))
