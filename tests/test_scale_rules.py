"""What must hold at any size: ids, frequent keys, hubs, exposure by blocks, options."""

import datetime as dt
import random
from dataclasses import replace

import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

from supplyrisk.functions.lattice import SETS
from supplyrisk.operators import baselines, exposure, measures, propagate, verdict, walks
from supplyrisk.operators.graph import BuildHistory
from supplyrisk.operators.windows import last_before
from supplyrisk.plans import compile as compiling
from supplyrisk.plans.compile import compile_graph
from supplyrisk.sources import build, copies, example
from supplyrisk.sources.schema import COPY, EDGES, RELEASE, VERTICES, code_of, copied_artifact, copy_host, hashed, pack, pack_copy


def graph_of(spark, vertices, edges):
    return BuildHistory(spark.createDataFrame([(v, t, a, None) for v, t, a in vertices], VERTICES), spark.createDataFrame([(-i - 1, s, d, label, None) for i, (label, s, d) in enumerate(edges)], EDGES))


def facts_of(spark, facts):
    return example.seeds(spark, facts)


def table_of(spark, schema, rows):
    return spark.createDataFrame(rows, schema)


# --- ids ------------------------------------------------------------------------------------


def test_keys_that_do_not_fit_fail(spark):
    one = spark.range(1)
    for key in (1 << 59, -1):
        with pytest.raises(Exception, match="does not fit"):
            one.select(pack(2, F.lit(key))).collect()
    with pytest.raises(Exception, match="host key does not fit"):
        one.select(pack_copy(pack(1, F.lit(4)), F.lit(2_097_159))).collect()
    with pytest.raises(Exception, match="artifact key does not fit"):
        one.select(pack_copy(pack(1, F.lit(1 << 30)), F.lit(7), 30)).collect()
    assert one.select(pack(2, F.lit(None).cast("long"))).first()[0] is None


def test_wide_hosts_have_their_own_copies(spark):
    df = spark.createDataFrame([(4, 2_097_159), (5, 7), (4, 7), (5, 2_097_159)], "artifact long, host long")
    copy = pack_copy(pack(1, F.col("artifact")), F.col("host"), 24)
    got = df.select("artifact", "host", copy.alias("c")).select("*", copied_artifact(F.col("c"), 24).alias("a"), copy_host(F.col("c"), 24).alias("h")).collect()
    assert len({r.c for r in got}) == 4 and all(r.h == r.host and r.a == (1 << 59) + r.artifact and r.c >> 59 == COPY for r in got)


def test_sources_are_told_apart_by_their_whole_name(spark):
    names = ["web1", "src1", "src", "web", "1", "", None, *[f"host{k}" for k in range(3000)]]
    df = spark.createDataFrame([(x,) for x in names], "source string")
    assert df.select(copies.host_id(F.col("source"))).distinct().count() == len(names) - 1  # null and empty are one


def small_tables(spark, path, supplier_shift, order_shift):
    rng = random.Random(3)
    day = lambda: dt.datetime(1996, 1, 1) + dt.timedelta(days=rng.randrange(300))
    orders = [(k << order_shift, k % 3, day()) for k in range(40)]
    lines = [(rng.choice(orders)[0], rng.randrange(6), rng.randrange(4) << supplier_shift, rng.choice("NRA"), rng.choice("OF")) for _ in range(150)]
    table_of(spark, "o_orderkey long, o_custkey long, o_orderdate timestamp", orders).write.parquet(f"{path}/orders.parquet")
    table_of(spark, "l_orderkey long, l_partkey long, l_suppkey long, l_returnflag string, l_linestatus string", lines).write.parquet(f"{path}/lineitem.parquet")
    table_of(spark, "p_partkey long, p_size int", [(k, 40 + k * 2) for k in range(6)]).write.parquet(f"{path}/part.parquet")
    table_of(spark, "s_suppkey long, s_acctbal double", [(k << supplier_shift, 1.0) for k in range(4)]).write.parquet(f"{path}/supplier.parquet")
    table_of(spark, "c_custkey long, c_acctbal double", [(k, 1.0) for k in range(3)]).write.parquet(f"{path}/customer.parquet")


def test_histories_of_wide_keys_agree_with_narrow_ones(spark, tmp_path):
    """The same history with keys that fit, that need wider hosts, and that must be numbered."""
    results, kinds = [], []
    for name, s, o in (("narrow", 0, 0), ("wide", 22, 0), ("numbered", 40, 20)):
        path = str(tmp_path / name)
        small_tables(spark, path, s, o)
        # part keys follow from order keys, so only their number must be the same
        kinds.append(build.copy_bits(spark, path))
        compiled = compile_graph(build.graph(spark, path), build.seeds(spark, path, "SV,SM")).staged()
        state = propagate.run(compiled)[0]
        bad = {r.vid - (RELEASE << 59) >> o: r.status for r in state.where(code_of(F.col("vid")) == RELEASE).collect()}
        parts = build.copy_parts(spark, path, state.where(code_of(F.col("vid")) == COPY)).collect()
        results.append((bad, sorted((r.supp_key >> s, r.status) for r in parts)))
    assert kinds == [21, 24, None]
    assert results[0] == results[1] and results[0][1]
    # with order keys in steps of 2^20 all releases are of part (key mod 6), so statuses differ, but not their make-up
    assert results[2][1] and {x for x, _ in results[2][1]} <= {0, 1, 2, 3}


# --- frequent keys ----------------------------------------------------------------------------


def test_last_before_is_the_same_for_frequent_keys(spark):
    rng = random.Random(5)
    rows = [(rng.choice([None, 1, 1, 1, 1, 2, 3, 4 + i % 50]), rng.randrange(300), i, rng.choice([None, None, i])) for i in range(3000)]
    df = spark.createDataFrame(rows, "key long, at long, id long, value long")
    plain = {r.id: r.x for r in last_before(df, "key", ["at", "id"], F.col("value"), "x").collect()}
    cut = {r.id: r.x for r in last_before(df, "key", ["at", "id"], F.col("value"), "x", hot_rows=100).collect()}
    window = Window.partitionBy("key").orderBy("at", "id").rowsBetween(Window.unboundedPreceding, -1)
    want = {r.id: r.x for r in df.withColumn("x", F.last("value", ignorenulls=True).over(window)).collect()}
    assert plain == want == cut and sum(x is not None for x in want.values()) > 2000


def many_copies(n):
    """One host that holds n copies of one identity and hands out n others; a chain behind each."""
    vertices = [(1, "host", None), (2, "host", None)]
    edges = []
    for k in range(n):
        vertices += [(100 + k, "artifact", "A"), (1000 + k, "artifact", "A"), (5000 + k, "artifact", "B")]
        edges += [("published_to", 100 + k, 1), ("fetched_from", 1, 1000 + k), ("published_to", 5000 + k, 2)]
    edges += [("published_to", 1000, 1), ("fetched_from", 2, 5000)]
    return vertices, edges


def test_copies_meet_in_hubs(spark):
    vertices, edges = many_copies(40)
    g = graph_of(spark, vertices, edges)
    for facts in ([("SM", 1000)], [("SV", 103)], [("SM", 100), ("SV", 1005)], [("SM", 5003)], []):
        compiled = compile_graph(g, facts_of(spark, facts))
        state = propagate.run(compiled)[0]
        got = {(r.host, r.artifact): r.context_status for r in verdict.contexts(compiled, state).collect()}
        status = {r.vid: r.status for r in state.collect()}
        held = {1: [100 + k for k in range(40)] + [1000], 2: [5000 + k for k in range(40)]}
        fetched = {1: [1000 + k for k in range(40)], 2: [5000]}
        want = {(h, a): max(status.get(x, 0) for x in held[h] if x != a) for h in (1, 2) for a in fetched[h]}
        assert got == want
        # every fetched artifact has at least the status of each other copy held
        assert all(status.get(a, 0) >= s for (h, a), s in want.items() if s)
        pairs = compile_graph(g, facts_of(spark, facts), predecessor_only=False)
        assert pairs.prop.where("label = 'copy'").count() <= 2 * (41 + 40) + 40
    plain = {r.vid: r.status for r in propagate.run(compile_graph(g, facts_of(spark, [("SM", 1000)])))[0].collect()}
    assert all(plain[1000 + k] == 2 for k in range(40))
    # only smaller ids: 1000 is fetched too, and greater than all that were published first
    only = {r.vid: r.status for r in propagate.run(compile_graph(g, facts_of(spark, [("SM", 139)]), predecessor_only=True))[0].collect()}
    assert all(only[1000 + k] == 2 for k in range(40))
    assert 1000 not in {r.vid for r in propagate.run(compile_graph(g, facts_of(spark, [("SM", 1005)]), predecessor_only=True))[0].collect()}


# --- exposure by blocks -------------------------------------------------------------------------


def random_graph(rng, n, cyclic):
    edges = set()
    for _ in range(3 * n):
        a, b = rng.sample(range(1, n), 2)
        edges.add((a, b) if cyclic or a < b else (b, a))
    return [(a << 40, b << 40, rng.choice([2, 3]), "feeds") for a, b in edges]


@pytest.mark.parametrize("cyclic", [False, True])
def test_exposure_counts_what_reach_lists(spark, cyclic):
    rng = random.Random(17 + cyclic)
    prop = spark.createDataFrame(random_graph(rng, 120, cyclic), "src long, dst long, mask int, label string")
    vertices = spark.createDataFrame([(v << 40, "artifact", None, None) for v in range(1, 125)], VERTICES)
    none = spark.createDataFrame([], "vid long, status int")
    compiled = compiling.Compiled(vertices, prop, none, spark.createDataFrame([], "host long, akey string, vid long, side string"), none.select("vid")).staged()
    starts = [(v << 40, 1 + v % 2) for v in range(1, 125)]  # the last ones touch no edge
    products = vertices.where("shiftright(vid, 40) % 3 = 0").select("vid")
    df = spark.createDataFrame(starts, "start long, need int").withColumn("vid", F.col("start"))
    listed = walks.reach(prop, df.select("start", "need")).join(products, "vid", "left_semi")
    want = {v: 0 for v, _ in starts} | {r.start: r["count"] for r in listed.groupBy("start").count().collect()}
    for options in (propagate.RunOptions(), propagate.RunOptions(local_cap=0)):
        got = {r.start: r.n for r in exposure.reach_counts(compiled, df, products, options).collect()}
        assert got == want
        members = df.select("start", F.when(F.col("start") % (3 << 40) == 0, "SM").otherwise("HV").alias("cls"), "vid")
        counts = {(r.vid, r.cls): r.n for r in exposure.class_counts(compiled, members, products, options).collect()}
        both = walks.reach(prop, df.select("start")).join(products, "vid", "left_semi").join(members.select("start", "cls"), "start")
        assert counts == {(r.vid, r.cls): r["count"] for r in both.groupBy("vid", "cls").count().collect()}


def test_set_sizes_equal_the_sets(spark, sf):
    compiled = compile_graph(build.graph(spark, sf), build.seeds(spark, sf, "SV,SM,HM,HV")).staged()
    state = propagate.run(compiled)[0]
    targets = compiled.vertices.where(code_of(F.col("vid")) == RELEASE).select(F.col("vid").alias("target"))
    some = targets.orderBy(F.xxhash64("target")).limit(15)
    want = {r.target: (r.n_sv, r.n_sm, r.n_hv, r.n_hm) for r in verdict.verdict_counts(verdict.verdict(compiled, some, state)).collect()}
    got = {r.target: (r.n_sv, r.n_sm, r.n_hv, r.n_hm) for r in measures.set_sizes(compiled, state, targets).collect()}
    assert len(got) == targets.count() and {t: got[t] for t in want} == want and any(w[3] for w in want.values())


def test_ranks_have_gaps_after_ties(spark):
    df = spark.createDataFrame([("a", 5), ("b", 7), ("c", 5), ("d", 0)], "x string, n long")
    assert {r.x: r.rank for r in measures.ranked(df, "n").collect()} == {"b": 1, "a": 2, "c": 2, "d": 4}


# --- options, parents, unions ---------------------------------------------------------------------


def test_options_of_verdicts(spark):
    compiled = compile_graph(example.graph(spark), example.seeds(spark, [("HV", 5), ("SV", 6)]))
    target = spark.createDataFrame([(9,)], "target long")
    assert verdict.verdict(compiled, target).first().hv == [5]
    ignored = compile_graph(example.graph(spark), example.seeds(spark, [("HV", 5), ("SV", 6)]), host_vuln="ignore")
    assert verdict.verdict(ignored, target).first().hv == []
    first = spark.createDataFrame([(2, [77], [9], [5], [1])], "status int, sv array<long>, sm array<long>, hv array<long>, hm array<long>")
    row = verdict.verdict(compiled, target, initial=first).first()
    assert (row.status, row.sv, row.sm, row.hv, row.hm) == (2, [6, 9, 77], [9], [5], [1])
    # a host that is weak of itself and hands on a malicious copy is in both sets, or in one
    g = example.graph(spark, {12: ("artifact", "A9")}, (("fetched_from", 11, 12),))
    both = compile_graph(g, example.seeds(spark, [("SM", 9), ("HV", 11)]))
    chain = spark.createDataFrame([(12,)], "target long")
    assert (lambda r: (r.hv, r.hm))(verdict.verdict(both, chain).first()) == ([11], [11])
    assert (lambda r: (r.hv, r.hm))(verdict.verdict(both, chain, disjoint_sets=True).first()) == ([], [11])
    union = verdict.verdict_union(verdict.verdict(compiled, spark.createDataFrame([(9,), (10,)], "target long"))).first()
    assert [union[x] for x in ("status", *SETS)] == [1, [6, 9, 10], [], [5], []]
    none = verdict.verdict_union(verdict.verdict(compiled, target).limit(0)).first()
    assert (none.status, none.sv) == (None, [])


def test_unknown_vertices_stay_malicious_when_facts_change(spark):
    g = example.graph(spark, extra_edges=(("feeds", 99, 8),))
    none = example.seeds(spark, [])
    for mode, want in (("malicious", 2), ("ignore", 0)):
        compiled = compile_graph(g, none, unknown=mode).staged().with_seeds(none)
        got = {r.vid: r.status for r in propagate.run(compiled)[0].collect()}
        assert got.get(9, 0) == want


def test_variants_equal_compiled_rule_sets(spark, sf):
    g = build.graph(spark, sf)
    g = BuildHistory(g.vertices.cache(), g.edges.cache())
    base, seeds = compile_graph(g).staged(), build.seeds(spark, sf, "SV,SM")
    rows = lambda c, options=None: {(r.vid, r.status) for r in propagate.run(c.with_seeds(seeds), "auto", options)[0].collect()}
    for rules, drop in (("max_impact", ()), ("parts_only", ()), ("paper", ("hosts_env",)), ("paper", ("hosts_env", "runs_step"))):
        want = rows(compile_graph(g, None, rules, drop))
        assert rows(base.variant(rules, drop)) == want
    assert rows(base.variant("paper", ("hosts_env",)), propagate.RunOptions(local_cap=0)) == rows(compile_graph(g, None, "paper", ("hosts_env",)))


def test_parents_and_attack_tree(spark):
    g = example.graph(spark)
    assert {r.parent for r in g.parents_of(spark.createDataFrame([(8,)], "vid long")).collect()} == {2, 6, 7}
    compiled = compile_graph(example.graph(spark, extra_edges=(("feeds", 4, 8),)), example.seeds(spark, [("SM", 4)]))
    tree = {(r.node, r.parent, r.depth, r.leaf) for r in baselines.attack_tree(compiled, 9, 10).collect()}
    # 4 is two steps away by the step and four by the host: both parents are there, at the least depth
    assert {(4, 8, 2, True), (4, 5, 2, True), (5, 7, 3, False), (9, None, 0, False)} <= tree


def test_run_log_counts_messages(spark):
    compiled = compile_graph(example.graph(spark), example.seeds(spark, [("SM", 4)])).laid_out(2)
    state, log = propagate.run(compiled, "semi_naive", propagate.RunOptions(local_cap=0))
    rows = log.frame(spark).orderBy("round").collect()
    assert [r.raised for r in rows] == [1, 1, 1, 2, 0] and [r.messages for r in rows] == [1, 1, 1, 2, 0]
    assert state.count() == 6 and all(r.shuffle_bytes >= 0 for r in rows)


def test_far_path_of_retraction(spark, sf):
    from supplyrisk.operators import incremental

    compiled = compile_graph(build.graph(spark, sf)).laid_out()
    full = propagate.run(compiled.with_seeds(build.seeds(spark, sf, "SV,SM")))[0]
    got = incremental.retract(full, compiled.with_seeds(build.seeds(spark, sf, "SV,SM")), build.seeds(spark, sf, "SM").select("vid"), build.seeds(spark, sf, "SV"), propagate.RunOptions(local_cap=0))
    want = propagate.run(compiled.with_seeds(build.seeds(spark, sf, "SV")))[0]
    assert {(r.vid, r.status) for r in got.collect()} == {(r.vid, r.status) for r in want.collect()}


def test_contraction_gives_back_every_vertex(spark, sf):
    compiled = compile_graph(build.graph(spark, sf), build.seeds(spark, sf, "SV,SM")).staged()
    small, gone = compiling.contract_steps(compiled)
    assert gone.count() > 1000 and small.prop.count() < compiled.n_edges
    want = {(r.vid, r.status) for r in propagate.run(compiled)[0].collect()}
    assert {(r.vid, r.status) for r in propagate.run(replace(compiled), "contracted")[0].collect()} == want


def test_hashed_names_keep_their_kind(spark):
    got = spark.createDataFrame([("a",), (None,)], "x string").select(code_of(hashed(11, F.col("x"))).alias("c")).collect()
    assert {r.c for r in got} == {11}
