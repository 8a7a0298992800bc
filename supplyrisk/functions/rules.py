"""Role rules as tables and columns, and their folding into transfer masks.

Every rule equals "greatest of what the incoming edges let through": an edge lets both
levels through (PASS) or only the top one (TOP_ONLY).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

PASS, TOP_ONLY = 3, 2

# Fixed values: (first, second, result) of each rule, 0 safe, 1 vulnerable, 2 malicious or compromised.
HOST_ROWS = ((0, 0, 0), (1, 0, 1), (2, 0, 2), (0, 2, 2), (1, 2, 2), (2, 2, 2))
STEP1_ROWS = ((0, 0, 0), (1, 0, 0), (2, 0, 2), (0, 1, 1), (1, 1, 1), (2, 1, 2), (0, 2, 2), (1, 2, 2), (2, 2, 2))
ENV_ROWS = ((0, 0, 0), (1, 0, 0), (2, 0, 2), (0, 1, 0), (1, 1, 0), (2, 1, 2), (0, 2, 2), (1, 2, 2), (2, 2, 2))
STEP2_ROWS = ((0, 0, 0), (1, 0, 1), (2, 0, 2), (0, 2, 2), (1, 2, 2), (2, 2, 2))
#: A host known to be vulnerable (no row of its own above): recorded, never passed on.
HOST_KNOWN_VULNERABLE_ROWS = ((0, 1, 1), (1, 1, 1), (2, 1, 2))

# Label, source type, target type of each legal edge.
LEGAL = (
    ("hosts_env", "host", "env"),
    ("runs_step", "env", "step"),
    ("feeds", "artifact", "step"),
    ("tools", "artifact", "step"),
    ("present_in", "artifact", "env"),
    ("present_in", "artifact", "host"),
    ("produces", "step", "artifact"),
    ("published_to", "artifact", "host"),
    ("fetched_from", "host", "artifact"),
)

#: What each edge lets through, by label and target type; published_to only makes copies findable.
TRANSFER = {
    ("feeds", "step"): PASS,
    ("tools", "step"): TOP_ONLY,
    ("runs_step", "step"): TOP_ONLY,
    ("hosts_env", "env"): TOP_ONLY,
    ("present_in", "env"): TOP_ONLY,
    ("present_in", "host"): PASS,
    ("produces", "artifact"): PASS,
    ("fetched_from", "artifact"): TOP_ONLY,
    ("copy", "artifact"): PASS,
}


def _only_top(level: Column) -> Column:
    return F.when(level == 2, 2).otherwise(0)


def host(present: Column, fact: Column) -> Column:
    return F.greatest(present, fact)


def step_phase1(tools: Column, others: Column) -> Column:
    return F.greatest(_only_top(tools), others)


def env(host: Column, present: Column) -> Column:
    return F.greatest(_only_top(host), _only_top(present))


def step_phase2(first: Column, env: Column) -> Column:
    return F.greatest(first, _only_top(env))


RULES = {"host": (host, HOST_ROWS), "step1": (step_phase1, STEP1_ROWS), "env": (env, ENV_ROWS), "step2": (step_phase2, STEP2_ROWS)}


def rule_rows(spark: SparkSession, name: str) -> DataFrame:
    """a, b of each printed row of a rule and what the rule's column makes of them."""
    function, rows = RULES[name]
    df = spark.createDataFrame([r[:2] for r in rows], "a int, b int")
    return df.withColumn("result", function(F.col("a"), F.col("b")).cast("int"))


def order_rules(lines: DataFrame) -> dict[str, DataFrame]:
    """order_key, a, b, result of each rule on every order. lines: order_key, use (held, tool, fed or
    present), level of what is used, breached (of its storage host).

    The steps' first phase and environment feed the second, the build host its environment."""
    most = lambda use: F.coalesce(F.max(F.when(F.col("use") == use, F.col("level"))), F.lit(0))
    breach = F.coalesce(F.max(F.when((F.col("use") == "held") & F.col("breached"), 2)), F.lit(0))
    each = lines.groupBy("order_key").agg(*[most(use).alias(use) for use in ("held", "tool", "fed", "present")], breach.alias("breach"))
    each = each.withColumns({"on_host": host(F.col("held"), F.col("breach")), "first": step_phase1(F.col("tool"), F.col("fed"))})
    each = each.withColumn("around", env(F.col("on_host"), F.col("present")))
    pairs = {"host": ("held", "breach"), "step1": ("tool", "fed"), "env": ("on_host", "present"), "step2": ("first", "around")}
    return {name: each.select("order_key", F.col(a).alias("a"), F.col(b).alias("b"), RULES[name][0](F.col(a), F.col(b)).cast("int").alias("result")) for name, (a, b) in pairs.items()}


def transfer_table(spark: SparkSession, rules: str = "paper") -> DataFrame:
    """label, dst_type, mask. max_impact: every edge lets everything through."""
    rows = [(label, kind, PASS if rules == "max_impact" else mask) for (label, kind), mask in TRANSFER.items()]
    return spark.createDataFrame(rows, "label string, dst_type string, mask int")


def passed(status: Column, mask: Column) -> Column:
    """Level that an edge hands on from its source's status; 0 is nothing."""
    return F.when((status == 2) & (mask.bitwiseAND(2) != 0), 2).when((status >= 1) & (mask.bitwiseAND(1) != 0), 1).otherwise(0)
