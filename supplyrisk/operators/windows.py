"""Windows that a frequent key does not put in one task."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Rows of one key beyond which its rows are cut into pieces, and pieces for each such key.
HOT_ROWS, PIECES = 1_000_000, 64


def last_before(rows: DataFrame, key: str, order: list[str], value: Column, name: str, hot_rows: int = HOT_ROWS, at_most: DataFrame | None = None) -> DataFrame:
    """rows with `name`: the last value that is not null among the rows of the key before each.

    order: first a number or timestamp. A key with more than hot_rows rows (there are fewer
    than rows / hot_rows of them) is cut by percentiles of that column; each piece is a
    window of its own, and the last value of the pieces before is carried over, as prefix
    sums are. Null keys are one key. at_most: key and n, no less than its rows, where that is
    cheaper to count than the rows themselves; they are counted if it shows a frequent key."""
    rows = rows.withColumn("__value", value)
    rare = at_most is not None and not at_most.where(F.col("n") > hot_rows).limit(1).count()
    hot = rows.groupBy(F.col(key).alias("__key")).agg(F.count("*").alias("__n")).where(F.col("__n") > hot_rows).select("__key")
    before = Window.orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    if rare or not hot.limit(1).count():
        return rows.withColumn(name, F.last("__value", ignorenulls=True).over(before.partitionBy(key))).drop("__value")
    hot = F.broadcast(hot.withColumn("__hot", F.lit(True)))
    known = rows.join(hot, rows[key].eqNullSafe(hot["__key"]), "left").drop("__key")
    place = F.col(order[0]).cast("double")
    steps = ", ".join(repr(i / PIECES) for i in range(1, PIECES))
    cuts = known.where("__hot").agg(F.expr(f"percentile_approx(cast({order[0]} AS double), array({steps}))").alias("c")).first()["c"]
    piece = F.size(F.filter(F.array(*[F.lit(float(c)) for c in sorted(set(cuts))]), lambda c: c <= place))
    known = known.withColumn("__piece", F.when(F.col("__hot"), piece).otherwise(0))
    inside = F.last("__value", ignorenulls=True).over(before.partitionBy(key, "__piece"))
    ends = known.where("__hot and __value is not null").groupBy(F.col(key).alias("__key"), F.col("__piece").alias("__of")).agg(F.max_by("__value", F.struct(*order)).alias("__last"))
    # One row for each piece of a hot key; each is sent to the pieces after it up to the next one.
    ends = ends.withColumn("__next", F.lead("__of").over(Window.partitionBy("__key").orderBy("__of")))
    carried = ends.select("__key", F.explode(F.sequence(F.col("__of") + 1, F.coalesce("__next", F.lit(PIECES)))).alias("__to"), "__last")
    met = known.withColumn("__inside", inside).join(F.broadcast(carried), F.col("__hot") & F.col(key).eqNullSafe(F.col("__key")) & (F.col("__piece") == F.col("__to")), "left")
    return met.withColumn(name, F.coalesce("__inside", "__last")).select(*[c for c in rows.columns if c != "__value"], name)
