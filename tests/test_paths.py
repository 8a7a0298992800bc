"""Pointer jumping, nearest facts, attack paths and build logs."""

import json
import random

import pytest

from supplyrisk.operators import jumping, propagate, verdict
from supplyrisk.plans import catalog
from supplyrisk.plans.compile import Compiled, compile_graph
from supplyrisk.sources import buildlog, example
from supplyrisk.sources.schema import hashed


def compiled_of(spark, n, edges, facts):
    vertices = spark.createDataFrame([(v, "artifact", None, None) for v in range(n)], "vid long, vtype string, akey string, props map<string,string>")
    prop = spark.createDataFrame([(s, d, m, "feeds") for s, d, m in edges], "src long, dst long, mask int, label string")
    none = spark.createDataFrame([], "host long, akey string, vid long, side string")
    return Compiled(vertices, prop, spark.createDataFrame(facts, "vid long, status int"), none, spark.createDataFrame([], "vid long"))


def statuses(edges, facts):
    state = dict(facts)
    for _ in range(2 * len(edges) + 2):
        for s, d, m in edges:
            level = state.get(s, 0)
            got = 2 if level == 2 and m & 2 else 1 if level and m & 1 else 0
            if got > state.get(d, 0):
                state[d] = got
    return {v: s for v, s in state.items() if s}


@pytest.mark.parametrize("seed", range(4))
def test_jumping_equals_plain_propagation(spark, seed):
    """Mostly linear, with branches, loops, cycles of single vertices and facts within stretches."""
    rng = random.Random(seed)
    n = 60
    edges = {(i, i + 1): rng.choice((2, 3, 3, 3)) for i in range(n - 21) if rng.random() < 0.9}
    edges |= {(40 + i, 40 + (i + 1) % 7): 3 for i in range(7)} | {(45, 50): 2, (50, 51): 3, (51, 52): 3, (5, 5): 3}
    edges |= {(rng.randrange(n), rng.randrange(40)): rng.choice((2, 3)) for _ in range(seed * 3)}
    rows = [(s, d, m) for (s, d), m in edges.items()]
    facts = {rng.randrange(n): rng.choice((1, 2)) for _ in range(5)} | {43: 1 + seed % 2}
    compiled = compiled_of(spark, n, rows, list(facts.items()))
    got = {r.vid: r.status for r in propagate.run(compiled, "jumping")[0].collect()}
    assert got == statuses(rows, facts)


def test_a_long_line_is_folded_whole(spark):
    n = 3000
    compiled = compiled_of(spark, n, [(i, i + 1, 3) for i in range(n - 1)], [(0, 2), (10, 1)])
    small, folded = jumping.fold_stretches(compiled)
    assert small.prop.count() == 0 and {r.root for r in folded.select("root").distinct().collect()} == {0}
    assert propagate.run(compiled, "jumping")[0].where("status = 2").count() == n


def test_no_edges(spark):
    assert [tuple(r) for r in propagate.run(compiled_of(spark, 3, [], [(1, 2)]), "jumping")[0].collect()] == [(1, 2)]


def test_nearest_facts(spark):
    c = compile_graph(example.graph(spark), example.seeds(spark, [("SM", 4), ("SM", 3), ("SM", 6)]))
    state = propagate.run(c)[0]
    rows = verdict.explain(c, state, 9, 5).orderBy("rank", "hop").collect()
    paths = {}
    for r in rows:
        paths.setdefault(r.rank, []).append((r.vid, r.label))
    assert [[v for v, _ in p] for _, p in sorted(paths.items())] == [[9, 8, 6], [9, 8, 7, 3], [9, 8, 7, 5, 4]]
    assert paths[3] == [(9, "produces"), (8, "runs_step"), (7, "hosts_env"), (5, "present_in"), (4, None)]
    assert {r.rank for r in verdict.explain(c, state, 9, 2).collect()} == {1, 2}


def test_a_fact_explains_itself(spark):
    c = compile_graph(example.graph(spark), example.seeds(spark, [("SM", 4)]))
    assert [tuple(r) for r in verdict.explain(c, propagate.run(c)[0], 4).collect()] == [(4, 1, 0, 4, None)]


def test_attack_paths_are_those_of_nearest_facts_here(spark, sf):
    got = {(r.target, r.fact): (r.hops, r.path) for r in catalog.udtf_attack_paths(spark, sf).collect()}
    flagged = [r.conv_id for r in example.instances(spark, sf).where("flagged").collect()]
    assert flagged and len(got) == 6 * len(flagged)
    for at in (16 * conv for conv in flagged):
        assert got[at + 9, at + 6] == (2, f"{at + 6} -feeds-> {at + 8} -produces-> {at + 9}") and got[at + 10, at + 4][0] == 4


def records():
    """The worked example as two build records."""
    return [
        {"step": "8", "env": "7", "host": "5", "inputs": ["6"], "tools": ["2"], "present": ["3"], "outputs": ["9", "10"]},
        {"step": "other", "inputs": None, "fetched": [{"artifact": "2", "host": "1"}, {"artifact": "6", "host": "1"}], "published": [{"artifact": "9", "host": "11"}]},
    ]


def test_build_log(spark, tmp_path):
    (tmp_path / "log").mkdir()
    text = "\n".join(json.dumps(r) for r in records())
    (tmp_path / "log" / "a.json").write_text(text + "\n\n" + text)
    (tmp_path / "log" / "_SUCCESS").write_text("")
    path = str(tmp_path / "log")
    whole = sorted(map(tuple, buildlog.read(spark, path).collect()))
    assert len(whole) == 2 * sum(len(list(buildlog.edges_of(r))) for r in records())
    for size in (17, 100):
        assert sorted(map(tuple, buildlog.read(spark, path, size).collect())) == whole
    g = buildlog.graph(buildlog.read(spark, path))
    assert g.validate(strict=True).count() == 0 and g.edges.count() == len(set(whole))
    ids = {r.name: r.vid for r in spark.createDataFrame([("6",), ("9",), ("10",)], "name string").select("name", hashed(1, spark_col("name")).alias("vid")).collect()}
    facts = spark.createDataFrame([(ids["6"], "SM", None, None, None, None)], "vid long, kind string, from_ts timestamp, to_ts timestamp, score double, source string")
    state = {r.vid: r.status for r in propagate.run(compile_graph(g, facts))[0].collect()}
    assert state[ids["9"]] == state[ids["10"]] == 2


def spark_col(name):
    from pyspark.sql import functions as F

    return F.col(name)


@pytest.mark.parametrize("line", ["{", "[]", "{}", '{"step": "a", "fetched": [1]}'])
def test_what_is_no_record_fails(spark, tmp_path, line):
    (tmp_path / "x.json").write_text(line)
    with pytest.raises(Exception, match="no build record at byte 0"):
        buildlog.read(spark, str(tmp_path / "x.json")).collect()


def test_empty_log(spark, tmp_path):
    (tmp_path / "x.json").write_text("")
    assert buildlog.read(spark, str(tmp_path)).count() == 0
