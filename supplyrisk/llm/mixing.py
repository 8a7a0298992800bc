"""Mixing sources to target weights by Pfair scheduling.

Documents of a source form blocks. A source of weight w has block j (from 1) released at
slot floor((j - 1) / w) and due by slot ceil(j / w); each slot goes to the released block
with the earliest deadline. Weights are the exact rational targets, not rounded to a period,
so at each slot every source is less than one block from its target. The plan has one row
per block. When a source is used up, its weight goes to the others and a new phase begins;
no document is dropped.
"""

from __future__ import annotations

import heapq
import math
from fractions import Fraction

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from supplyrisk.llm.common import bucket_count, order_key, partitions, range_of, stage

#: Documents in a block at least, and the power of a source's size that is its default weight.
BLOCK_DOCS = 64
TEMPERATURE = 0.5
#: Blocks that are planned at most, but for one of each source: the plan is made on the
#: driver (about 200 bytes and 10 microseconds each), so larger inputs have larger blocks.
MAX_BLOCKS = 1_000_000


def whole_weights(weights: dict[str, float], period: int) -> dict[str, int]:
    """Blocks per period of each source: at least one, `period` together, by largest remainders."""
    names = sorted(weights)
    period = max(period, len(names))
    total = sum(weights.values())
    spare = period - len(names)
    exact = {x: spare * weights[x] / total for x in names}
    out = {x: 1 + int(exact[x]) for x in names}
    for x in sorted(names, key=lambda x: (int(exact[x]) - exact[x], x))[: period - sum(out.values())]:
        out[x] += 1
    return out


def pfair_period(shares: dict[str, int]) -> list[str]:
    """The source that gets each slot of one period: earliest deadline first among released blocks."""
    period = sum(shares.values())
    waiting = [[] for _ in range(period)]  # by release slot
    for name, w in shares.items():
        for j in range(w):
            waiting[j * period // w].append((-(-(j + 1) * period // w), -(-period // w), name))
    ready: list[tuple] = []
    out = []
    for slot in range(period):
        for block in waiting[slot]:
            heapq.heappush(ready, block)
        out.append(heapq.heappop(ready)[2])
    return out


def plan_blocks(blocks: dict[str, int], weights: dict[str, float], period: int | None = None) -> list[tuple[str, int, int, int]]:
    """Source, block, phase and slot of every block, by slot; with a period, for targets rounded to it.

    Of equal deadlines the greater weight goes first, so at the start of a phase, when every
    source has a block released, they follow in one fixed order; a phase costs what it emits."""
    if bad := [x for x in blocks if not weights[x] > 0]:
        raise ValueError(f"weights must be above zero: {bad[:5]}")
    exact = {x: Fraction(weights[x]) for x in blocks}
    scale = math.lcm(1, *(f.denominator for f in exact.values()))
    share = {x: int(f * scale) for x, f in exact.items()}
    order = sorted(blocks, key=lambda x: (-share[x], x))
    after = list(range(1, len(order) + 2))  # a list of the sources left, from place 0; its end is len(order)
    before = list(range(-1, len(order) + 1))
    first, total = 0, sum(share.values())
    done, out, phase = dict.fromkeys(blocks, 0), [], 0
    while first < len(order):
        if period is not None:
            share = whole_weights({x: weights[x] for x in blocks if done[x] < blocks[x]}, period)
            order = sorted(share, key=lambda x: (-share[x], x))
            first, total, after, before = 0, sum(share.values()), list(range(1, len(order) + 2)), list(range(-1, len(order) + 1))
        begin, fresh = len(out), first
        waiting: list[tuple[int, int, int]] = []  # release, place, number in the phase
        ready: list[tuple[int, int, int]] = []  # deadline, place, number in the phase
        while True:
            while waiting and waiting[0][0] <= len(out) - begin:
                _, at, j = heapq.heappop(waiting)
                heapq.heappush(ready, (-(-j * total // share[order[at]]), at, j))
            if fresh < len(order) and (not ready or (-(-total // share[order[fresh]]), fresh, 1) < ready[0]):
                at, j, fresh = fresh, 1, after[fresh]
            else:
                _, at, j = heapq.heappop(ready)
            x = order[at]
            out.append((x, done[x], phase, len(out)))
            done[x] += 1
            if done[x] == blocks[x]:
                break
            heapq.heappush(waiting, (j * total // share[x], at, j + 1))
        total -= share[x]
        if at == first:
            first = after[at]
        else:
            after[before[at]] = after[at]
        before[after[at]] = before[at]
        phase += 1
        if period is not None and all(done[y] == blocks[y] for y in order):
            break
    return out


def _placed(docs: DataFrame, weights: dict[str, float] | None, block_docs: int | None, period: int | None, id_col: str, source_col: str, tie: Column, max_blocks: int) -> DataFrame:
    """doc_id, source, tie, block, within, phase, slot of every row; rows of a source in the
    order of id and tie."""
    spark = docs.sparkSession
    name = F.coalesce(F.concat(F.lit("="), F.col(source_col).cast("string")), F.lit("?"))
    rows = stage(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(source_col).cast("string").alias("source"), name.alias("name"), order_key(id_col).alias("k"), tie.alias("tie")), "mix-rows")
    n = rows.count()
    # The top 52 bits of the tie as a share: what is less there is less in the tie.
    part = (F.shiftright("tie", 12) + F.lit(1 << 51)) / F.lit(2.0**52)
    dealt = rows.withColumn("range", range_of(rows, "k", bucket_count(n, partitions(spark)), part))
    totals = dealt.groupBy("name", "range").agg(F.count("*").alias("n"))
    offsets = totals.select("name", "range", F.coalesce(F.sum("n").over(Window.partitionBy("name").orderBy("range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    inside = Window.partitionBy("range", "name").orderBy("k", "tie")
    numbered = dealt.withColumn("i", F.row_number().over(inside)).join(offsets, ["name", "range"])
    sizes = {r["name"]: r["n"] for r in totals.groupBy("name").agg(F.sum("n").alias("n")).collect()}  # a row per source
    size = block_docs or max(BLOCK_DOCS, -(-n // max_blocks))
    numbered = numbered.withColumn("i", F.col("i") + F.col("before") - 1).withColumn("block", F.floor(F.col("i") / size))
    if weights:
        given = {"=" + k if k is not None else "?": v for k, v in weights.items()}
        least = min(given.values())
        target = {x: given.get(x, least) for x in sizes}
    else:
        target = {x: c**TEMPERATURE for x, c in sizes.items()}
    plan = plan_blocks({x: -(-c // size) for x, c in sizes.items()}, target, period)
    slots = spark.createDataFrame(plan, "name string, block long, phase int, slot long")
    placed = numbered.join(slots, ["name", "block"])
    return placed.select("doc_id", "source", "tie", "block", (F.col("i") % size).cast("int").alias("within"), "phase", "slot")


def mix_sources(docs: DataFrame, weights: dict[str, float] | None = None, block_docs: int | None = None, period: int | None = None, id_col: str = "doc_id", source_col: str = "source", max_blocks: int = MAX_BLOCKS) -> DataFrame:
    """doc_id, source, block (from 0), within, phase, slot of every row.

    slot orders blocks (blocks of equal slots do not exist); within orders a block's rows.
    weights: by source, above zero; default size to the power TEMPERATURE; sources without a
    weight get the least one. A null source is a source of its own. Rows of a source are taken
    in id order (null first); rows of equal ids in any order. Empty input: no rows. The driver
    sees one row per source and range and plans one slot per block; block_docs None gives
    blocks of BLOCK_DOCS rows, or larger ones so that there are about max_blocks. A source, or
    a null id, that holds most rows is numbered by ranges, so no task gets all of it.
    period: None for exact targets, else they are rounded to whole blocks of so many slots."""
    spread = F.xxhash64(F.spark_partition_id(), F.monotonically_increasing_id())  # rows of one id are interchangeable
    return _placed(docs, weights, block_docs, period, id_col, source_col, spread, max_blocks).drop("tie")


def mixed_order(docs: DataFrame, weights: dict[str, float] | None = None, block_docs: int | None = None, period: int | None = None, id_col: str = "doc_id", source_col: str = "source", max_blocks: int = MAX_BLOCKS) -> DataFrame:
    """The same rows and columns, stored order being the mix (blocks by slot). Options as in
    mix_sources; rows with equal id, source and other columns share a place."""
    tie = F.xxhash64(*[c for c in docs.columns if "map<" not in docs.schema[c].dataType.simpleString()])  # maps have no hash
    places = _placed(docs, weights, block_docs, period, id_col, source_col, tie, max_blocks)
    places = places.groupBy(F.col("doc_id").alias("__id"), F.col("tie").alias("__tie")).agg(F.min(F.struct("slot", "within")).alias("__place"))
    known = docs.withColumns({"__id2": F.col(id_col).cast("long"), "__tie2": tie, "__row": F.monotonically_increasing_id()})
    placed = known.join(places, F.col("__id2").eqNullSafe(F.col("__id")) & (F.col("__tie2") == F.col("__tie")))
    return placed.sort("__place.slot", "__place.within", "__row").select(*[docs[c] for c in docs.columns])
