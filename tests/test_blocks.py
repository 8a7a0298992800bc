"""Graphs beyond one task, solved block by block."""

from pyspark.sql import functions as F

from supplyrisk.operators import blocks, incremental, propagate
from supplyrisk.plans.compile import LABELS, compile_graph
from supplyrisk.sources import build

FAR = propagate.RunOptions(local_cap=0)


def rows(state):
    return sorted(map(tuple, state.collect()))


def _compiled(spark, sf, kinds="SV,SM"):
    compiled = compile_graph(build.graph(spark, sf), build.seeds(spark, sf, kinds))
    compiled.home = build.home(spark, sf)
    return compiled.staged()


def test_a_graph_beyond_one_task_is_finished_by_blocks(spark, sf):
    compiled = _compiled(spark, sf, "SV,SM,HV,HM")
    expected = rows(propagate.run(compiled, "finisher")[0])
    at = compiled.in_blocks()
    for mode in ("finisher", "auto", "two_phase"):
        assert rows(propagate.run(at, mode, FAR)[0]) == expected
    assert at.variant("max_impact").blocks is at.blocks  # laid out once for all rule sets
    flat = compiled.variant("max_impact")
    assert rows(propagate.run(at.variant("max_impact"), "auto", FAR)[0]) == rows(propagate.run(flat)[0])


def test_late_facts_start_from_the_kept_state(spark, sf):
    at = _compiled(spark, sf).in_blocks()
    weak = propagate.run(at.with_seeds(build.seeds(spark, sf, "SV")), "auto", FAR)[0]
    assert rows(incremental.update(weak, at, build.seeds(spark, sf, "SM,HM"), FAR)) == rows(propagate.run(at.with_seeds(build.seeds(spark, sf, "SV,SM,HM")))[0])


def test_vertices_without_edges_or_unknown_keep_their_level(spark):
    prop = spark.createDataFrame([(1, 2, 3, "feeds"), (2, 9, 3, "feeds")], "src long, dst long, mask int, label string")
    laid = blocks.lay_out(prop, spark.createDataFrame([(1,), (2,), (5,)], "vid long"), LABELS, 2)
    seeds = spark.createDataFrame([(1, 1), (5, 2), (77, 2)], "vid long, status int")
    assert rows(blocks.solve(laid, None, seeds)) == [(1, 1), (2, 1), (5, 2), (9, 1), (77, 2)]


def test_rounds_do_not_shuffle_the_blocks(spark, sf):
    at = _compiled(spark, sf).in_blocks().blocks
    sent = spark.createDataFrame([(0, 1)], "block int, x int").repartition(at.n, "block").groupBy("block").agg(F.collect_list("x").alias("parts"))
    plan = at.table.join(sent.hint("shuffle_hash"), "block")._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1


def test_starts_are_spread_by_blocks(spark, sf, monkeypatch):
    from supplyrisk.operators import exposure, measures, verdict, walks
    from supplyrisk.sources.schema import RELEASE, code_of

    near = _compiled(spark, sf, "SV,SM,HM")
    at = near.in_blocks()
    products = near.vertices.select("vid").where(code_of(F.col("vid")) == RELEASE)
    monkeypatch.setattr(blocks, "WORDS", 1)
    assert rows(measures.blast_radius(at, at.seeds, products, FAR)) == rows(measures.blast_radius(near, near.seeds, products))
    start = near.seeds.where("status = 2").select(F.col("vid").alias("start"))
    pairs = walks.reach(near.prop, start).groupBy("start").agg(F.count("*").alias("n"), F.max("hops").alias("hops"))
    assert rows(exposure.reach_hops(at, start.withColumn("need", F.lit(3)), FAR)) == rows(pairs)
    some = products.orderBy("vid").limit(8).withColumnRenamed("vid", "target")
    assert rows(verdict.verdict_members(at, some, propagate.run(near)[0], FAR)) == rows(verdict.verdict_members(near, some, propagate.run(near)[0]))
