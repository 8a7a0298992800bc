"""Random small histories against direct descent, and all execution modes against each other."""

import random

import pytest

from supplyrisk.operators import propagate, verdict, walks
from supplyrisk.operators.baselines import recursive_eval, sql_recursive
from supplyrisk.operators.graph import BuildHistory
from supplyrisk.plans.compile import compile_graph
from supplyrisk.sources.example import seeds as seed_frame
from supplyrisk.sources.schema import EDGES, VERTICES

KINDS = ("artifact", "step", "host", "env")
LABELS = {("artifact", "step"): ("feeds", "tools"), ("artifact", "env"): ("present_in",), ("artifact", "host"): ("present_in", "published_to"), ("host", "env"): ("hosts_env",), ("env", "step"): ("runs_step",), ("step", "artifact"): ("produces",), ("host", "artifact"): ("fetched_from",)}


def history(seed, n, base=0):
    rng = random.Random(seed)
    vertices = []
    for i in range(n):
        kind = rng.choices(KINDS, (5, 2, 2, 1))[0]
        vertices.append((base + i, kind, f"K{base}-{rng.randrange(3)}" if kind == "artifact" else None))
    edges = []
    for i in range(n):
        for j in range(i + 1, n):
            labels = LABELS.get((vertices[i][1], vertices[j][1]))
            if labels and rng.random() < 0.35:
                edges.append((rng.choice(labels), base + i, base + j))
    facts = []
    for v, kind, _ in vertices:
        if kind in ("artifact", "host") and rng.random() < 0.25:
            facts.append((("S" if kind == "artifact" else "H") + rng.choice("VVM"), v))
    return vertices, edges, facts


@pytest.fixture(scope="module")
def many(spark):
    """Forty disjoint histories in one graph."""
    parts = [history(k, 14, 1000 * k) for k in range(40)]
    vertices = [v for p in parts for v in p[0]]
    edges = [e for p in parts for e in p[1]]
    facts = [f for p in parts for f in p[2]]
    g = BuildHistory(spark.createDataFrame([(v, t, a, None) for v, t, a in vertices], VERTICES).cache(), spark.createDataFrame([(-i - 1, s, d, label, None) for i, (label, s, d) in enumerate(edges)], EDGES).cache())
    return parts, g, seed_frame(spark, facts)


def test_verdicts_equal_direct_descent(spark, many):
    parts, g, seeds = many
    compiled = compile_graph(g, seeds).laid_out()
    targets = [v for p in parts for v, t, _ in p[0] if t == "artifact"]
    got = {r.target: (r.status, *map(frozenset, (r.sv, r.sm, r.hv, r.hm))) for r in verdict.verdict(compiled, spark.createDataFrame([(t,) for t in targets], "target long")).collect()}
    want = {t: recursive_eval(*parts[t // 1000], t) for t in targets}
    assert {t: (got[t], want[t]) for t in targets if got[t] != want[t]} == {}
    assert len({w[0] for w in want.values()}) == 3
    for status, sv, sm, hv, hm in want.values():
        assert (status == 2) == bool(sm or hm) and not sv & sm


def test_modes_agree(spark, many):
    _, g, seeds = many
    compiled = compile_graph(g, seeds).laid_out(4)
    results = {}
    for mode in ("finisher", "semi_naive", "two_phase", "contracted", "jumping", "levels"):
        options = propagate.RunOptions(compact_every=2)
        results[mode] = {(r.vid, r.status) for r in propagate.run(compiled, mode, options)[0].collect()}
    assert results["finisher"] and all(r == results["finisher"] for r in results.values())
    acyclic = {(r.vid, r.status) for r in sql_recursive(compile_graph(*history_frames(spark, 3))).collect()}
    assert acyclic == {(r.vid, r.status) for r in propagate.run(compile_graph(*history_frames(spark, 3)))[0].collect()}


def history_frames(spark, seed):
    vertices, edges, facts = history(seed, 12)
    g = BuildHistory(spark.createDataFrame([(v, t, a, None) for v, t, a in vertices], VERTICES), spark.createDataFrame([(-i - 1, s, d, label, None) for i, (label, s, d) in enumerate(edges)], EDGES))
    return g, seed_frame(spark, facts)


def test_order_of_methods(spark, many):
    _, g, seeds = many
    by = {r: {x.vid: x.status for x in propagate.run(compile_graph(g, seeds, r))[0].collect()} for r in ("paper", "max_impact", "parts_only")}
    artifacts = {r.vid for r in g.vertices.where("vtype = 'artifact'").collect()}
    for v in artifacts:
        assert by["parts_only"].get(v, 0) <= by["paper"].get(v, 0) <= by["max_impact"].get(v, 0)


def test_more_facts_never_lower(spark, many):
    _, g, seeds = many
    few = {x.vid: x.status for x in propagate.run(compile_graph(g, seeds.where("kind like '%V'")))[0].collect()}
    all_ = {x.vid: x.status for x in propagate.run(compile_graph(g, seeds))[0].collect()}
    assert all(all_.get(v, 0) >= s for v, s in few.items())


def test_reach_levels_components_distributed(spark, many):
    _, g, seeds = many
    compiled = compile_graph(g, seeds)
    prop, vertices = compiled.prop.cache(), compiled.vertices
    start = vertices.where("vid % 1000 < 3").selectExpr("vid AS start")
    a, b = (sorted(map(tuple, walks.reach(prop, start, d, 2, distributed=x).collect())) for d, x in (("forward", True), ("forward", False)))
    assert a == b and a
    a, b = (sorted(map(tuple, walks.reach(prop, start, "backward", 1, distributed=x).collect())) for x in (True, False))
    assert a == b
    a, b = ({r.vid: r.level for r in walks.topo_levels(prop, vertices, distributed=x).collect()} for x in (True, False))
    assert a == b and None not in a.values()
    comp = {r.vid: r.component for r in walks.components(prop, vertices).collect()}
    near = {}
    for r in prop.collect():
        near.setdefault(r.src, set()).add(r.dst)
        near.setdefault(r.dst, set()).add(r.src)
    for v in comp:
        seen, todo = {v}, [v]
        while todo:
            for w in near.get(todo.pop(), ()):
                if w not in seen:
                    seen.add(w)
                    todo.append(w)
        assert comp[v] == min(seen)


def test_cycle_terminates_and_is_found(spark):
    vertices = [(1, "artifact", "a", None), (2, "host", None, None), (3, "artifact", "b", None), (4, "artifact", "c", None)]
    edges = [(-1, 1, 2, "present_in", None), (-2, 2, 1, "fetched_from", None), (-3, 2, 3, "fetched_from", None)]
    g = BuildHistory(spark.createDataFrame(vertices, VERTICES), spark.createDataFrame(edges, EDGES))
    compiled = compile_graph(g, seed_frame(spark, [("SM", 1)]))
    for mode in ("finisher", "semi_naive", "two_phase", "levels"):
        assert {(r.vid, r.status) for r in propagate.run(compiled, mode)[0].collect()} == {(1, 2), (2, 2), (3, 2)}
    assert {r.vid for r in walks.find_cycles(compiled.prop, compiled.vertices).collect()} == {1, 2}
