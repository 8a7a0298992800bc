"""Rule tables, masks, graph checks and the worked example."""

import itertools

import pytest
from pyspark.sql import functions as F

from supplyrisk.functions import lattice, rules
from supplyrisk.operators import propagate, verdict
from supplyrisk.plans.compile import compile_graph
from supplyrisk.sources import example
from supplyrisk.sources.schema import EDGES


@pytest.mark.parametrize("name", list(rules.RULES))
def test_rule_columns_match_the_tables(spark, name):
    got = {(r.a, r.b): r.result for r in rules.rule_rows(spark, name).collect()}
    assert got == {(a, b): c for a, b, c in rules.RULES[name][1]}


def test_known_vulnerable_host_rows(spark):
    for present, fact, result in rules.HOST_KNOWN_VULNERABLE_ROWS:
        assert spark.range(1).select(rules.host(F.lit(present), F.lit(fact))).first()[0] == result


def test_masks_equal_tables_for_all_parents(spark):
    """Greatest of what the masks let through, against the step and env tables."""
    rows = [(t, f, h, p) for t, f, h, p in itertools.product(range(3), repeat=4)]
    df = spark.createDataFrame(rows, "t int, f int, h int, p int")
    env = rules.env(F.col("h"), F.col("p"))
    step = rules.step_phase2(rules.step_phase1(F.col("t"), F.col("f")), env)
    through = lambda c, m: rules.passed(F.col(c), F.lit(m))
    folded_env = F.greatest(through("h", 2), through("p", 2))
    folded = F.greatest(through("t", 2), through("f", 3), rules.passed(folded_env, F.lit(2)))
    assert df.where((env != folded_env) | (step != folded)).count() == 0


def test_legal_and_illegal_edges(spark):
    g = example.graph(spark)
    assert g.validate(strict=True).count() == 0
    assert g.check_identity().count() == 0
    kinds = {"artifact": 2, "step": 8, "host": 5, "env": 7}
    labels = {x[0] for x in rules.LEGAL}
    triples = list(itertools.product(sorted(labels), kinds, kinds))
    edges = [(i, kinds[s], kinds[d], label, None) for i, (label, s, d) in enumerate(triples)]
    bad = type(g)(g.vertices, spark.createDataFrame(edges, EDGES)).validate()
    assert {triples[r.eid] for r in bad.collect()} == set(triples) - set(rules.LEGAL)


CASES = [
    ([], 0, "", "", "", ""),
    ([("SV", 2), ("SV", 3), ("SV", 4)], 0, "2,3,4", "", "5", ""),
    ([("SV", 6)], 1, "6,9", "", "", ""),
    ([("SM", 4)], 2, "", "4,9", "", "5"),
    ([("HM", 5)], 2, "", "9", "", "5"),
    ([("HM", 1)], 2, "", "2,6,9", "", "1"),
    ([("SM", 2)], 2, "", "2,9", "", ""),
    ([("HV", 5)], 0, "", "", "5", ""),
]


@pytest.mark.parametrize("facts,status,sv,sm,hv,hm", CASES)
def test_worked_example(spark, facts, status, sv, sm, hv, hm):
    compiled = compile_graph(example.graph(spark), example.seeds(spark, facts))
    row = verdict.verdict(compiled, spark.createDataFrame([(9,)], "target long")).first()
    assert (row.status, *[",".join(map(str, row[s])) for s in lattice.SETS]) == (status, sv, sm, hv, hm)


def test_dangling_parent_is_malicious(spark):
    compiled = compile_graph(example.graph(spark, extra_edges=(("feeds", 99, 8),)), example.seeds(spark, []))
    row = verdict.verdict(compiled, spark.createDataFrame([(9,)], "target long")).first()
    assert (row.status, row.sm, row.sv, row.hm) == (2, [9], [], [])
    with pytest.raises(ValueError):
        compile_graph(example.graph(spark, extra_edges=(("feeds", 99, 8),)), unknown="error")


def test_host_is_tainted_for_one_chain_only(spark):
    g = example.graph(spark, {12: ("artifact", "A9"), 13: ("artifact", "A10")}, (("fetched_from", 11, 12), ("fetched_from", 11, 13)))
    compiled = compile_graph(g, example.seeds(spark, [("SM", 9)]))
    got = {r.target: r for r in verdict.verdict(compiled, spark.createDataFrame([(12,), (13,)], "target long")).collect()}
    assert (got[12].status, got[12].sm, got[12].hm) == (2, [9, 12], [11])
    assert (got[13].status, got[13].sm, got[13].hm) == (0, [], [])
    state, _ = propagate.run(compiled)
    assert {(r.host, r.artifact) for r in verdict.tainted_distribution(compiled, state).collect()} == {(11, 12)}
    ctx = spark.createDataFrame([(11, 12)], "host long, artifact long")
    assert verdict.verdict(compiled, spark.createDataFrame([(11,)], "target long"), context=ctx).first().status == 2
    assert verdict.verdict(compiled, spark.createDataFrame([(11,)], "target long")).first().status == 0
