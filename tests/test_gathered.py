"""Graphs beyond one task, finished by numbers; compiled edges straight from the lines."""

import shutil

import pytest
from pyspark.sql import functions as F

from supplyrisk.operators import blocks, gathered, incremental, propagate
from supplyrisk.plans import catalog
from supplyrisk.plans.compile import LABELS, compile_graph
from supplyrisk.sources import build

FAR = propagate.RunOptions(local_cap=0)
BY_ROUNDS = propagate.RunOptions(local_cap=0, gather_cap=0)


def rows(state):
    return sorted(map(tuple, state.collect()))


def _compiled(spark, sf, kinds="SV,SM"):
    compiled = compile_graph(build.graph(spark, sf), build.seeds(spark, sf, kinds))
    compiled.home = build.home(spark, sf)
    return compiled.staged()


@pytest.mark.parametrize("cyclic", [False, True])
def test_folded_edges_are_those_of_the_compiled_graph(spark, sf, cyclic):
    expected, got = compile_graph(build.graph(spark, sf, cyclic)), catalog._folded(spark, sf, cyclic)
    for name, columns in (("prop", ["src", "dst", "mask", "label"]), ("vertices", ["vid", "vtype"]), ("copies", ["host", "akey", "vid", "side"]), ("unknown", ["vid"])):
        assert rows(getattr(got, name).select(*columns)) == rows(getattr(expected, name).select(*columns)), name
    bare = got.vertices.select("vid").exceptAll(got.ends.select("vid")).join(got.prop.withColumnRenamed("src", "vid"), "vid", "left_anti")
    assert not bare.count()


def test_missing_references_are_compiled_in_full(spark, sf, tmp_path):
    path = str(tmp_path / "sf")
    shutil.copytree(sf, path)
    assert build.is_whole(spark, path)
    some = spark.read.parquet(f"{sf}/supplier.parquet").where("s_suppkey <> 0").toPandas()
    (tmp_path / "sf" / "supplier.parquet").unlink()
    some.to_parquet(f"{path}/supplier.parquet")
    assert not build.is_whole(spark, path)
    assert rows(catalog._compiled(spark, path, "SV").unknown)


def test_by_numbers_as_by_rounds(spark, sf):
    at = _compiled(spark, sf, "SV,SM,HV,HM").in_blocks()
    for one in (at, at.variant("max_impact"), at.variant("parts_only")):
        assert rows(propagate.run(one, "auto", FAR)[0]) == rows(propagate.run(one, "auto", BY_ROUNDS)[0])
    weak = propagate.run(at.with_seeds(build.seeds(spark, sf, "SV")), "auto", FAR)[0]
    late = build.seeds(spark, sf, "SM,HM")
    assert rows(incremental.update(weak, at, late, FAR)) == rows(incremental.update(weak, at, late, BY_ROUNDS))


def test_numbers_of_unknown_and_lonely_vertices(spark):
    prop = spark.createDataFrame([(1, 2, 3, "feeds"), (2, 9, 3, "feeds"), (9, 2, 2, "tools")], "src long, dst long, mask int, label string")
    laid = blocks.lay_out(prop, spark.createDataFrame([(1,), (2,), (5,)], "vid long"), LABELS, 3)
    seeds = spark.createDataFrame([(1, 1), (5, 2), (77, 2)], "vid long, status int")
    # 77 is nowhere: it keeps its level, as by rounds
    assert rows(gathered.solve(laid, None, seeds)) == rows(blocks.solve(laid, None, seeds)) == [(1, 1), (2, 1), (5, 2), (9, 1), (77, 2)]


def test_ranks_and_grades_by_numbers(spark, sf):
    from supplyrisk.operators import extensions, walks

    at = _compiled(spark, sf).in_blocks()
    assert rows(walks.topo_levels(at.prop, at.vertices, laid=at.blocks)) == rows(walks.topo_levels(at.prop, at.vertices))
    factors = spark.createDataFrame([(v.vid, 0.5 + (v.vid % 499) / 1000) for v in at.vertices.where("vtype = 'host'").collect()], "vid long, factor double")
    scores = at.seeds.select("vid", F.col("status").cast("double").alias("score"))
    near = rows(extensions.graded(at, scores, {"produces": 0.9}, "fetched_from", factors, BY_ROUNDS))
    assert rows(extensions.graded(at, scores, {"produces": 0.9}, "fetched_from", factors)) == near


def test_what_is_behind_a_cycle_has_no_rank(spark):
    cyclic = spark.createDataFrame([(1, 2, 3, "feeds"), (2, 3, 3, "feeds"), (3, 2, 3, "feeds"), (2, 4, 3, "feeds")], "src long, dst long, mask int, label string")
    laid = blocks.lay_out(cyclic, spark.createDataFrame([(4,), (6,)], "vid long"), LABELS, 4)
    assert rows(gathered.ranks(laid).na.fill(-1)) == [(1, 0), (2, -1), (3, -1), (4, -1), (6, 0)]


def test_timed_facts_act_as_on_the_edges_left(spark):
    from supplyrisk.operators import extensions
    from supplyrisk.plans.compile import Compiled

    t = lambda day: f"2024-01-{day:02d} 00:00:00"
    use = spark.createDataFrame([(1, 2, t(5)), (1, 3, t(25))], "src long, dst long, used_at string").withColumn("used_at", F.col("used_at").cast("timestamp"))
    facts = spark.createDataFrame([(1, t(1), t(10))], "vid long, from_ts string, to_ts string").select("vid", *[F.col(x).cast("timestamp").alias(x) for x in ("from_ts", "to_ts")])
    edges = [(1, 2, 2, "fetched_from"), (1, 3, 2, "fetched_from"), (2, 4, 3, "feeds"), (3, 5, 3, "feeds")]
    seeds = spark.createDataFrame([(1, 2)], "vid long, status int")
    vertices = spark.createDataFrame([(v, "artifact") for v in range(1, 6)], "vid long, vtype string")
    for more, expected in (([], [(1, 2), (2, 2), (4, 2)]), ([(4, 1, 3, "feeds")], [(1, 2), (2, 2), (4, 2)])):
        prop = spark.createDataFrame(edges + more, "src long, dst long, mask int, label string")
        assert rows(extensions.temporal_status(Compiled(vertices, prop, seeds, None, None), use, facts)) == expected


def test_starts_are_counted_by_numbers(spark, sf, monkeypatch):
    from supplyrisk.operators import exposure
    from supplyrisk.sources.schema import RELEASE, code_of

    at = _compiled(spark, sf).in_blocks()
    monkeypatch.setattr(gathered, "SLOTS", 2)
    products = at.vertices.select("vid").where(code_of(F.col("vid")) == RELEASE)
    hosts = at.vertices.where("vtype = 'host'").select(F.col("vid").alias("start"), "vid", F.when(F.col("vid") % 2 == 0, 2).otherwise(1).alias("need"))
    assert hosts.count() > 64
    assert rows(exposure.reach_counts(at, hosts, products, FAR)) == rows(exposure.reach_counts(at, hosts, products))


def test_starts_on_cycles_are_counted(spark):
    prop = spark.createDataFrame([(1, 2, 3, "feeds"), (2, 3, 3, "feeds"), (3, 2, 3, "feeds"), (3, 4, 3, "feeds"), (5, 4, 3, "feeds")], "src long, dst long, mask int, label string")
    laid = blocks.lay_out(prop, spark.createDataFrame([(4,)], "vid long"), LABELS, 5)
    starts = spark.createDataFrame([(i, i, 3) for i in range(1, 6)], "number long, vid long, need int")
    assert rows(gathered.reach_counts(laid, None, starts, starts.select("vid"))) == [(1, 4), (2, 3), (3, 3), (4, 1), (5, 2)]


def test_hosts_are_counted_beyond_what_every_task_holds(spark, monkeypatch):
    # a long line of steps is shrunk to a vertex for each start and product, whatever the edges
    from supplyrisk.operators import exposure
    from supplyrisk.plans.compile import Compiled

    prop = spark.createDataFrame([(i, i + 1, 3, "feeds") for i in range(1, 200)] + [(1000, 150, 2, "feeds")], "src long, dst long, mask int, label string")
    none = spark.createDataFrame([], "vid long, status int")
    vertices = spark.createDataFrame([(v, "host") for v in (*range(1, 201), 1000, 1001)], "vid long, vtype string")
    at = Compiled(vertices, prop, none, none, none.select("vid")).in_blocks()
    starts = spark.createDataFrame([(1, 1, 2), (120, 120, 2), (1000, 1000, 2), (1001, 1001, 2), (3000, 120, 1), (3000, 1000, 1)], "start long, vid long, need int")
    products = spark.createDataFrame([(100,), (200,), (1001,)], "vid long")
    monkeypatch.setattr(gathered, "SPREAD_CAP", 20)
    monkeypatch.setattr(exposure, "_spread", lambda *_: pytest.fail("starts were spread by rounds"))
    assert rows(exposure.reach_counts(at, starts, products, FAR)) == [(1, 2), (120, 1), (1000, 1), (1001, 1), (3000, 1)]
