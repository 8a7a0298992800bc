"""Conversations as linear lineage: each turn is an input of the step that makes the next."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from supplyrisk.operators.graph import BuildHistory
from supplyrisk.sources.schema import CHAIN_ENV, CHAIN_HOST, CHAIN_STEP, TURN, pack
from supplyrisk.sources.tables import table

TURN_BITS = 20


def _key(conv: F.Column, turn: F.Column) -> F.Column:
    return F.shiftleft(conv.cast("long"), TURN_BITS).bitwiseOR(turn.cast("long"))


def graph(spark: SparkSession, sf_dir: str) -> BuildHistory:
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role")
    no = F.lit(None).cast("map<string,string>").alias("props")
    said = turns.where("role <> 'system'")
    after = Window.partitionBy("conv_id").orderBy("turn")
    linked = said.withColumn("next", F.lead("turn").over(after)).where("next is not null")
    vid, step = pack(TURN, _key(F.col("conv_id"), F.col("turn"))), pack(CHAIN_STEP, _key(F.col("conv_id"), F.col("next")))
    made = pack(TURN, _key(F.col("conv_id"), F.col("next")))
    env, host = pack(CHAIN_ENV, F.col("conv_id")), pack(CHAIN_HOST, F.col("conv_id"))
    convs = turns.select("conv_id").distinct()

    def edge(df: DataFrame, src: F.Column, dst: F.Column, label: str) -> DataFrame:
        return df.select(src.alias("src"), dst.alias("dst"), F.lit(label).alias("label"))

    edges = edge(linked, vid, step, "feeds").unionAll(edge(linked, step, made, "produces")).unionAll(edge(linked, env, step, "runs_step")).unionAll(edge(convs, host, env, "hosts_env")).unionAll(edge(turns.where("role = 'system'"), vid, env, "present_in"))
    name = F.concat_ws("/", F.col("conv_id").cast("string"), F.col("turn").cast("string"))
    vertices = turns.select(vid.alias("vid"), F.lit("artifact").alias("vtype"), name.alias("akey"), no)
    for df, v, kind in ((linked, step, "step"), (convs, env, "env"), (convs, host, "host")):
        vertices = vertices.unionAll(df.select(v.alias("vid"), F.lit(kind).alias("vtype"), F.lit(None).cast("string").alias("akey"), no))
    return BuildHistory(vertices, edges.select((-1 - F.xxhash64("src", "dst", "label").bitwiseAND(F.lit(2**62 - 1))).alias("eid"), "src", "dst", "label", no))


def seeds(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = table(spark, sf_dir, "conversations")
    vid = pack(TURN, _key(F.col("conv_id"), F.col("turn"))).alias("vid")
    return turns.where("length(text) % 17 = 0").select(vid, F.lit("SV").alias("kind")).unionAll(turns.where("length(text) % 41 = 0").select(vid, F.lit("SM").alias("kind")))
