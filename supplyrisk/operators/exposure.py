"""How many products each of many starts reaches, and how many starts reach each target.

Starts are worked on 64 at a time: a vertex holds one long whose bits say which starts of a
block reach it, so pairs of starts and vertices are never rows. Graphs of checked size are
solved in tasks of some blocks each, which read the edges laid out once; larger ones are thinned
and shrunk in one task and swept by all (operators/gathered.py, shrunk.py), or go by a loop whose
messages are reduced by bit_or before they move.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from supplyrisk.operators import blocks, gathered, shrunk
from supplyrisk.operators.kernels import Csr
from supplyrisk.operators.propagate import RunOptions
from supplyrisk.plans.compile import Compiled
from supplyrisk.plans.staging import Staged, partitions


def _numbered(starts: DataFrame) -> DataFrame:
    """start, cls, need of each distinct start with its block and bit; kept, so numbers stay."""
    rows = starts.select("start", "cls", F.col("need").cast("int").alias("need")).distinct().withColumn("i", F.monotonically_increasing_id())
    return Staged(rows.select("start", "cls", "need", F.shiftright("i", 6).alias("block"), F.col("i").bitwiseAND(F.lit(63)).cast("int").alias("bit")), "starts").df


class Spread:
    """Bits of a block's starts over a laid-out graph."""

    def __init__(self, csr: Csr):
        self.csr = csr
        src, n = csr.src, len(csr.ids)
        waits, level = np.bincount(csr.dst, minlength=n), np.full(n, -1, np.int64)
        frontier, at = np.flatnonzero(waits == 0), 0
        while len(frontier):
            level[frontier] = at
            e = csr.out(frontier)
            np.subtract.at(waits, csr.dst[e], 1)
            new = np.unique(csr.dst[e])
            frontier, at = new[waits[new] == 0], at + 1
        self.cyclic = bool((level < 0).any())
        self.steps = {}
        for need in (1, 2):
            on = np.flatnonzero(csr.mask & need)
            order = on[np.argsort(level[src[on]], kind="stable")]
            cuts = np.searchsorted(level[src[order]], np.arange(at + 1))
            self.steps[need] = (src[order], csr.dst[order], cuts)

    def run(self, vertex: np.ndarray, bits: np.ndarray, need: int) -> np.ndarray:
        held = np.zeros(len(self.csr.ids), np.uint64)
        np.bitwise_or.at(held, vertex, bits)
        src, dst, cuts = self.steps[need]
        while True:
            before = held.copy() if self.cyclic else None
            for a, b in zip([0, *cuts], [*cuts, len(src)], strict=True):  # what is on or behind a cycle has level -1, so is first
                given = held[src[a:b]]
                on = np.flatnonzero(given)
                if len(on):
                    np.bitwise_or.at(held, dst[a:b][on], given[on])
            if not self.cyclic or (before == held).all():
                return held


def _in_tasks(compiled: Compiled, starts: DataFrame, wanted: DataFrame) -> DataFrame:
    """start and n."""
    spark = compiled.prop.sparkSession
    tasks = partitions(spark)
    null = lambda *names: [F.lit(None).cast("binary" if x == "blob" else "long").alias(x) for x in names]
    each = F.explode(F.sequence(F.lit(0), F.lit(tasks - 1))).alias("task")
    rows = starts.select(F.pmod("block", F.lit(tasks)).cast("int").alias("task"), "block", "vid", "start", F.col("need").cast("long").alias("need"), F.col("bit").cast("long").alias("bit"), *null("blob"))
    graph = compiled.packed.select(each, *null("block", "vid", "start", "need", "bit"), "blob")
    targets = wanted.select("vid").distinct().select(each, *null("block"), "vid", *null("start", "need", "bit", "blob"))
    masks = compiled.masks

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        columns = ("block", "vid", "start", "need", "bit")
        kept, wanted_ids, csr = {c: [] for c in columns}, [], None
        for b in batches:
            if not b.num_rows:
                continue
            is_start = b.column(b.schema.get_field_index("block")).is_valid().to_numpy(zero_copy_only=False)
            blob = b.column(b.schema.get_field_index("blob"))
            has_blob = blob.is_valid().to_numpy(zero_copy_only=False)
            for i in np.flatnonzero(has_blob):
                csr = Csr.unpacked(blob[int(i)].as_buffer().to_pybytes()).remasked(masks)
            for c in columns:
                kept[c].append(b.column(b.schema.get_field_index(c)).fill_null(0).to_numpy(zero_copy_only=False)[is_start])
            wanted_ids.append(b.column(b.schema.get_field_index("vid")).fill_null(0).to_numpy(zero_copy_only=False)[~is_start & ~has_blob])
        if csr is None or not sum(map(len, kept["block"])):
            return
        block, vid, start, need, bit = (np.concatenate(kept[c]) for c in columns)
        target = np.concatenate(wanted_ids)
        spread, ids = Spread(csr), csr.ids

        def placed(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            at = np.minimum(np.searchsorted(ids, x), max(len(ids) - 1, 0))
            return at, ids[at] == x if len(ids) else np.zeros(len(x), bool)

        place, inside = placed(vid)
        target_place, target_inside = placed(target)
        out_start, out_n = [], []
        order = np.lexsort((need, block))
        edges = np.flatnonzero(np.diff(block[order], prepend=-1) | np.diff(need[order], prepend=-1))
        for s, e in zip(edges, np.append(edges, len(order))[1:], strict=True):
            rows_ = order[s:e]
            mine = np.uint64(1) << bit[rows_].astype(np.uint64)
            on = inside[rows_]
            held = spread.run(place[rows_][on], mine[on], int(need[rows_[0]]))[target_place] if len(ids) else np.zeros(len(target), np.uint64)
            held = np.where(target_inside, held, np.uint64(0))
            for k in np.flatnonzero(~on):  # no edge touches it: it reaches itself
                held[target == vid[rows_[k]]] |= mine[k]
            counts = np.unpackbits(held.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
            first = np.unique(bit[rows_], return_index=True)[1]
            out_start += start[rows_][first].tolist()
            out_n += counts[bit[rows_][first]].tolist()
        yield pa.RecordBatch.from_arrays([pa.array(out_start, pa.int64()), pa.array(out_n, pa.int64())], names=["start", "n"])

    dealt = rows.unionAll(graph).unionAll(targets).repartitionById(tasks, F.col("task"))
    return dealt.mapInArrow(run, "start long, n long")


def _spread(compiled: Compiled, starts: DataFrame, options: RunOptions) -> DataFrame:
    """block, need, vid, bits of all that is reached: block by block where the graph is laid out so, else by
    a loop of joins."""
    if compiled.blocks is not None:
        return blocks.spread(compiled.blocks, compiled.masks, starts, options.max_rounds)
    edges = compiled.prop.select(F.col("src").alias("vid"), F.col("dst").alias("next"), "mask")
    one = F.expr("shiftleft(1L, bit)")
    state = Staged(starts.groupBy("block", "need", "vid").agg(F.bit_or(one).alias("bits")), "spread").df
    frontier = state
    key = ["block", "need", "vid"]
    for _ in range(options.max_rounds):
        if not frontier.limit(1).count():
            return state
        sent = frontier.join(edges, "vid").where(F.col("mask").bitwiseAND(F.col("need")) != 0).groupBy("block", "need", F.col("next").alias("vid")).agg(F.bit_or("bits").alias("bits"))
        fresh = sent.join(state.withColumnRenamed("bits", "old"), key, "left").select(*key, F.col("bits").bitwiseAND(F.bitwise_not(F.coalesce("old", F.lit(0).cast("long")))).alias("bits")).where("bits <> 0")
        frontier = Staged(fresh, "spread").df
        state = Staged(state.unionAll(frontier).groupBy(*key).agg(F.bit_or("bits").alias("bits")), "spread").df
    raise RuntimeError("no fixpoint")


def _small(compiled: Compiled, options: RunOptions) -> bool:
    return compiled.packed is not None and (compiled.n_edges or 0) <= options.local_cap


def reach_counts(compiled: Compiled, starts: DataFrame, products: DataFrame, options: RunOptions | None = None) -> DataFrame:
    """start, n: how many of the products (vid) each start reaches, itself included.

    starts: start, vid (where it begins; several rows give several places) and need (mask
    bits, any of which lets it through an edge); one need for each start. Every start is
    counted, none reached gives 0."""
    options = options or RunOptions()
    starts = starts.withColumn("cls", F.lit(""))
    numbers = _numbered(starts)
    dealt = starts.select("start", "vid").join(numbers, "start")
    of, got = (F.shiftleft("block", 6) + F.col("bit")).alias("number"), None
    if not _small(compiled, options) and compiled.blocks is not None and gathered.number(compiled.blocks).m <= min(gathered.GATHER_CAP, options.gather_cap):
        got = gathered.reach_counts(compiled.blocks, compiled.masks, dealt.select(of, "vid", "need"), products)
    if _small(compiled, options):
        counted = _in_tasks(compiled, dealt, products)
    elif got is not None:
        counted = got.join(numbers.select(of, "start"), "number").select("start", "n")
    else:
        held = _spread(compiled, dealt, options).join(products.select("vid").distinct(), "vid", "left_semi")
        bits = [F.sum(F.shiftrightunsigned("bits", i).bitwiseAND(F.lit(1).cast("long"))) for i in range(64)]
        per_block = held.groupBy("block", "need").agg(F.array(*bits).alias("n"))
        counted = per_block.select("block", "need", F.posexplode("n").alias("bit", "n")).join(numbers, ["block", "need", "bit"]).select("start", "n")
    return numbers.select("start").join(counted, "start", "left").select("start", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


def reach_hops(compiled: Compiled, starts: DataFrame, options: RunOptions | None = None) -> DataFrame:
    """start, n, hops: how many vertices each start (a vertex, with need as in reach_counts) reaches,
    itself included, and in how many hops at most. Pairs are never rows."""
    options = options or RunOptions()
    at = compiled.in_blocks()
    numbers = _numbered(starts.withColumn("cls", F.lit("")))
    if gathered.number(at.blocks).m <= min(gathered.GATHER_CAP, options.gather_cap):
        number = (F.shiftleft("block", 6) + F.col("bit")).alias("number")
        got = gathered.reach_hops(at.blocks, at.masks, numbers.select(number, F.col("start").alias("vid"), "need"))
        if got is not None:
            return got.join(numbers.select(number, "start"), "number").select("start", "n", "hops")
    got = blocks.spread(at.blocks, at.masks, numbers.withColumn("vid", F.col("start")), options.max_rounds, by_hop=True)
    return numbers.join(got, ["block", "bit"]).select("start", "n", "hops")


def ancestors(compiled: Compiled, targets: DataFrame, options: RunOptions | None = None) -> DataFrame:
    """start, vid of all that reaches each target (column `start`), itself included, block by block."""
    options = options or RunOptions()
    prop = compiled.prop.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "mask", *(["label"] if "label" in compiled.prop.columns else []))
    extra = targets.select(F.col("start").alias("vid")).unionAll(compiled.vertices.select("vid")).unionAll(prop.select(F.col("dst").alias("vid")))
    laid = blocks.lay_out(prop, extra, (), compiled.n_edges or prop.count(), compiled.home)
    numbers = _numbered(targets.select("start", F.lit("").alias("cls"), F.lit(3).alias("need")))
    held = blocks.spread(laid, None, numbers.withColumn("vid", F.col("start")), options.max_rounds)
    bit = F.explode(F.filter(F.sequence(F.lit(0), F.lit(63)), lambda i: F.getbit(F.col("bits"), i) == 1)).alias("bit")
    return held.select("block", "vid", bit).join(F.broadcast(numbers.select("block", "bit", "start")), ["block", "bit"]).select("start", "vid")


def _by_weights(compiled: Compiled, members: DataFrame, targets: DataFrame) -> DataFrame:
    """vid, cls, n as class_counts, of a graph of checked size: one task shrinks it, every task sweeps a share of what starts are left."""
    spark = compiled.prop.sparkSession
    tasks, masks = partitions(spark), compiled.masks
    members = Staged(members.select("start", "cls", "vid"), "members").df
    classes = sorted(r["cls"] for r in members.select("cls").distinct().collect())
    if not classes:
        return spark.createDataFrame([], "vid long, cls string, n long")
    null = lambda *names: [F.lit(None).cast("binary" if x == "blob" else "int" if x == "cls" else "long").alias(x) for x in names]
    code = (F.array_position(F.array(*[F.lit(x) for x in classes]), F.col("cls")) - 1).cast("int").alias("cls")
    rows = compiled.packed.select("blob", *null("start", "cls", "vid")).unionAll(members.select(*null("blob"), "start", code, "vid")).unionAll(Staged(targets.select("vid"), "targets").df.select(*null("blob", "start", "cls"), "vid"))

    def shrink(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, got, wanted = [], [], [np.empty(0, np.int64)]
        for b in batches:
            blob, cls = b.column(0), b.column(2)
            is_blob, is_member = (x.is_valid().to_numpy(zero_copy_only=False) for x in (blob, cls))
            for i in np.flatnonzero(is_blob):
                csr = Csr.unpacked(blob[int(i)].as_buffer().to_pybytes()).remasked(masks)
                on = csr.mask & 2 != 0  # the greatest level passes every edge
                parts.append((csr.ids.copy(), csr.src[on].astype(np.int32), csr.dst[on]))
            start, vid = (b.column(i).fill_null(0).to_numpy(zero_copy_only=False) for i in (1, 3))
            got.append((start[is_member], cls.fill_null(0).to_numpy(zero_copy_only=False)[is_member], vid[is_member]))
            wanted.append(vid[~is_blob & ~is_member])
        start, cls, vid = (np.concatenate(x) for x in zip(*got, strict=True))
        target = np.unique(np.concatenate(wanted))
        ids = shrunk.distinct(np.concatenate([vid, target, *[p[0] for p in parts]]))
        src, dst = [np.empty(0, np.int32)], [np.empty(0, np.int32)]
        while parts:
            own, s, d = parts.pop()
            at = np.searchsorted(ids, own).astype(np.int32)
            src.append(at[s])
            dst.append(at[d])
        graph, name = shrunk.shrink(len(ids), np.concatenate(src), np.concatenate(dst), start, cls, np.searchsorted(ids, vid), len(classes), np.searchsorted(ids, target))
        yield pa.RecordBatch.from_arrays([pa.array([True, False]), pa.array([shrunk.saved(**graph), shrunk.saved(vid=target, name=name)], pa.binary())], names=["is_graph", "blob"])

    small = Staged(rows.coalesce(1).mapInArrow(shrink, "is_graph boolean, blob binary"), "shrunk", "lz4").df

    def sweep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                total = shrunk.sweeps(shrunk.loaded(b.column(1)[i].as_py()), b.column(0)[i].as_py(), tasks)
                yield pa.RecordBatch.from_arrays([pa.array([shrunk.saved(total=total.astype(np.int32) if total.max(initial=0) < 1 << 31 else total)], pa.binary())], names=["blob"])

    each = F.explode(F.sequence(F.lit(0), F.lit(tasks - 1))).alias("task")
    dealt = small.where("is_graph").select(each, "blob").repartitionById(tasks, F.col("task"))
    swept = Staged(dealt.mapInArrow(sweep, "blob binary"), "swept", "lz4").df

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, at = 0, None
        for b in batches:
            for i in range(b.num_rows):
                row = shrunk.loaded(b.column(0)[i].as_py())
                if "total" in row:
                    total = total + row["total"].astype(np.int64)
                else:
                    at = row
        for k, cls in enumerate(classes):
            n = total[at["name"], k]
            on = np.flatnonzero(n)
            for i in range(0, len(on), 500_000):
                x = on[i : i + 500_000]
                yield pa.RecordBatch.from_arrays([pa.array(at["vid"][x]), pa.array([cls] * len(x), pa.string()), pa.array(n[x])], names=["vid", "cls", "n"])

    parts = swept.unionAll(small.where("not is_graph").select("blob"))
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    old = spark.conf.get(key)
    spark.conf.set(key, "1")  # a row is some megabytes
    try:
        return Staged(parts.coalesce(1).mapInArrow(add, "vid long, cls string, n long"), "class-counts").df
    finally:
        spark.conf.set(key, old)


def class_counts(compiled: Compiled, members: DataFrame, targets: DataFrame, options: RunOptions | None = None) -> DataFrame:
    """vid, cls, n: how many members of each class reach each target (vid); absent if none.

    members: start (a member's number, one for each class), cls, vid (where it begins)."""
    options = options or RunOptions()
    if _small(compiled, options):
        return _by_weights(compiled, members, targets)
    if compiled.blocks is not None and (compiled.n_edges or 0) <= min(gathered.SPREAD_CAP, options.gather_cap):
        return gathered.class_counts(compiled.blocks, compiled.masks, members, targets)
    starts = members.select("start", "cls", "vid").withColumn("need", F.lit(2))  # the greatest level passes every edge
    numbers = _numbered(starts)
    dealt = starts.select("start", "cls", "vid").join(numbers, ["start", "cls"])
    masks = numbers.groupBy("block", "need", "cls").agg(F.bit_or(F.expr("shiftleft(1L, bit)")).alias("of"))
    held = _spread(compiled, dealt, options).join(targets.select("vid").distinct(), "vid", "left_semi")
    parts = held.join(masks, ["block", "need"]).select("vid", "cls", F.bit_count(F.col("bits").bitwiseAND(F.col("of"))).cast("long").alias("n"))
    return parts.groupBy("vid", "cls").agg(F.sum("n").alias("n")).where("n > 0")
