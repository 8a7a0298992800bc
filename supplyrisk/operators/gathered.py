"""Whole laid-out graphs of checked size, finished in one task.

Vertices of all blocks are numbered through, so edges are 5 bytes and no ids are needed to solve: one task
reads them block by block (about 13 bytes for each edge of a build history are held), facts are turned into
numbers and results into ids by all tasks. Statuses, ranks and grades take one pass instead of a job a round.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from copy import deepcopy
from dataclasses import dataclass
from decimal import ROUND_HALF_UP, Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from supplyrisk.operators import shrunk
from supplyrisk.operators.blocks import Blocks, bucketed
from supplyrisk.operators.kernels import Csr
from supplyrisk.plans.staging import Staged, partitions

#: Edges up to which one task may hold a graph by numbers.
GATHER_CAP = 150_000_000
#: Edges, or vertices of a frontier, looked at together.
CHUNK = 1_000_000


@dataclass
class Numbered:
    """table: block, ids, degree, dst, mask of each block's own vertices; offset: the first number of each block."""

    table: DataFrame
    offset: dict[int, int]
    n: int
    m: int


def _owners(buffer: pa.Buffer, n: int) -> np.ndarray:
    return np.frombuffer(buffer, np.int32, n, buffer.size - 4 * n)


def _each(function: Callable[..., Iterator[dict]], schema: pa.Schema):
    """Rows as dicts of Arrow values in, one batch for each dict out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                for row in function(*[b.column(k)[i] for k in range(b.num_columns)]):
                    yield pa.RecordBatch.from_arrays([pa.array([row[f.name]], f.type) for f in schema], schema=schema)

    return run


def number(blocks: Blocks) -> Numbered:
    """Made once for each layout: owners say which numbers the far ends of a block's edges have."""
    if blocks.numbered is not None:
        return blocks.numbered
    offset, n = {}, 0
    for r in blocks.table.select("block", "own").orderBy("block").collect():  # a row for each block
        offset[r["block"]] = n
        n += r["own"]

    def ask(block: pa.Scalar, blob: pa.Scalar) -> Iterator[dict]:
        me, buffer = block.as_py(), blob.as_buffer()
        ids = Csr.unpacked(buffer).ids
        if not len(ids):
            return
        owner = _owners(buffer, len(ids))
        order = np.argsort(owner, kind="stable")
        where, first = np.unique(owner[order], return_index=True)
        for w, part in zip(where, np.split(ids[order], first[1:]), strict=True):
            if w != me:
                yield {"block": int(w), "by": me, "ids": part.tobytes()}

    asked = blocks.table.select("block", "blob").mapInArrow(_each(ask, pa.schema([("block", pa.int32()), ("by", pa.int32()), ("ids", pa.binary())])), "block int, by int, ids binary")

    def answer(block: pa.Scalar, blob: pa.Scalar, asked: pa.Scalar) -> Iterator[dict]:
        me, buffer = block.as_py(), blob.as_buffer()
        ids = Csr.unpacked(buffer).ids
        own = ids[_owners(buffer, len(ids)) == me]
        by, wanted = asked.values.field("by"), asked.values.field("ids")
        for i in range(len(by)):
            ids = np.frombuffer(wanted[i].as_buffer(), np.int64)
            at = np.searchsorted(own, ids)
            if not len(own) or at.max() >= len(own) or (own[at] != ids).any():
                raise ValueError("an edge ends at a vertex that does not exist")
            yield {"block": by[i].as_py(), "of": me, "at": at.astype(np.int32).tobytes()}

    lists = asked.repartition(blocks.n, "block").groupBy("block").agg(F.collect_list(F.struct("by", "ids")).alias("asked"))
    answered = blocks.table.join(lists.hint("shuffle_hash"), "block").select("block", "blob", "asked").mapInArrow(_each(answer, pa.schema([("block", pa.int32()), ("of", pa.int32()), ("at", pa.binary())])), "block int, of int, at binary")

    def assemble(block: pa.Scalar, blob: pa.Scalar, told: pa.Scalar) -> Iterator[dict]:
        me, buffer = block.as_py(), blob.as_buffer()
        csr = Csr.unpacked(buffer)
        owner = _owners(buffer, len(csr.ids))
        own = owner == me
        new = np.empty(len(csr.ids), np.int32)
        new[own] = offset[me] + np.arange(int(own.sum()))
        if told.is_valid:
            of, at = told.values.field("of"), told.values.field("at")
            for i in range(len(of)):
                new[owner == of[i].as_py()] = offset[of[i].as_py()] + np.frombuffer(at[i].as_buffer(), np.int32)
        degree = np.diff(csr.start)[own].astype(np.int32)  # edges start at a block's own vertices alone
        yield {"block": me, "ids": csr.ids[own].tobytes(), "degree": degree.tobytes(), "dst": new[csr.dst].tobytes(), "mask": csr.mask.tobytes(), "m": len(csr.dst)}

    told = answered.repartition(blocks.n, "block").groupBy("block").agg(F.collect_list(F.struct("of", "at")).alias("told"))
    fields = [("block", pa.int32()), ("ids", pa.binary()), ("degree", pa.binary()), ("dst", pa.binary()), ("mask", pa.binary()), ("m", pa.int64())]
    slim = blocks.table.join(told.hint("shuffle_hash"), "block", "left").select("block", "blob", "told").mapInArrow(_each(assemble, pa.schema(fields)), "block int, ids binary, degree binary, dst binary, mask binary, m long")
    table = bucketed(slim, blocks.n, "numbered")
    blocks.numbered = Numbered(table, offset, n, table.agg(F.sum("m")).first()[0] or 0)
    return blocks.numbered


def _placed(blocks: Blocks, at: Numbered, rows: DataFrame) -> DataFrame:
    """kind, numbers, vids (without a number) and values of rows (vid, kind, value), by block and kind."""
    offset = at.offset

    def place(block: pa.Scalar, ids: pa.Scalar, kind: pa.Scalar, vids: pa.Scalar, values: pa.Scalar) -> Iterator[dict]:
        own = np.frombuffer(ids.as_buffer(), np.int64)
        vid, value = vids.values.to_numpy(zero_copy_only=False), values.values.to_numpy(zero_copy_only=False)
        i = np.minimum(np.searchsorted(own, vid), max(len(own) - 1, 0))
        inside = own[i] == vid if len(own) else np.zeros(len(vid), bool)
        yield {"kind": kind.as_py(), "numbers": (i[inside] + offset[block.as_py()]).astype(np.int32).tobytes(), "values": value[inside].astype(np.float64).tobytes(), "vids": vid[~inside].tolist()}

    fields = pa.schema([("kind", pa.int32()), ("numbers", pa.binary()), ("values", pa.binary()), ("vids", pa.list_(pa.int64()))])
    lists = rows.groupBy(blocks.block_of(F.col("vid")).alias("block"), "kind").agg(F.collect_list(F.struct("vid", "value")).alias("x")).select("block", "kind", F.col("x.vid").alias("vids"), F.col("x.value").alias("values"))
    met = at.table.select("block", "ids").join(lists.repartition(blocks.n, "block").hint("shuffle_hash"), "block").select("block", "ids", "kind", "vids", "values")
    return Staged(met.mapInArrow(_each(place, fields), "kind int, numbers binary, values binary, vids array<bigint>"), "placed", "lz4").df


class Whole:
    """All edges by the number of their source."""

    def __init__(self, n: int, m: int):
        self.n, self.m, self.at, self.parts = n, m, 0, []
        self.start, self.degree = np.zeros(n, np.int32), np.zeros(n, np.int32)
        self.dst, self.mask = np.empty(m, np.int32), np.empty(m, np.int8)

    def add(self, first: int, degree: np.ndarray, dst: np.ndarray, mask: np.ndarray) -> None:
        here = slice(first, first + len(degree))
        self.parts.append((first, len(degree)))
        self.degree[here] = degree
        self.start[here] = self.at + np.cumsum(degree) - degree
        self.dst[self.at : self.at + len(dst)] = dst
        self.mask[self.at : self.at + len(dst)] = mask
        self.at += len(dst)

    def remask(self, masks: tuple[int, ...] | None) -> None:
        """As Csr.remasked, in place."""
        for k in range(0, self.m, CHUNK):
            part = self.mask[k : k + CHUNK]
            if masks is None:
                part &= 3
            else:
                new = np.array([min(x, 3) if x >= 0 else -1 for x in masks], np.int8)[part >> 2]
                part[:] = np.where(new < 0, part & 3, new)

    def leaving(self, front: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Edges that leave a frontier, with the place in it of each one's source, some at a time."""
        for k in range(0, max(len(front), 1), CHUNK):
            here = front[k : k + CHUNK]
            size = self.degree[here].astype(np.int64)
            piece = np.cumsum(size) // CHUNK
            for part in np.split(np.arange(len(here)), np.flatnonzero(np.diff(piece)) + 1):
                s = size[part]
                e = np.repeat(self.start[here[part]] - (np.cumsum(s) - s), s) + np.arange(int(s.sum()))
                yield e, np.repeat(k + part, s)

    def settle(self, level: np.ndarray, start: np.ndarray, to: int, need: int | None = None) -> None:
        """Raise start to a level and send it on, over the edges that hand it on or those with a bit of `need`."""
        need = need or (2 if to == 2 else 1)
        new = np.unique(start[level[start] < to])
        level[new] = to
        while len(new):
            rose = []
            for e, _ in self.leaving(new):
                d = self.dst[e[self.mask[e] & need != 0]]
                d = np.unique(d[level[d] < to])
                level[d] = to
                rose.append(d)
            new = np.concatenate(rose)

    def reached(self, start: np.ndarray, need: int) -> tuple[np.ndarray, int, np.ndarray, np.ndarray]:
        """New numbers of what is reached over edges with a bit of `need` (-1: it is not), how many, and the ends of
        these edges. What the edges were held in is given up."""
        alive = np.zeros(self.n, np.int8)
        self.settle(alive, start, 1, need)
        self.start, alive = None, alive.view(bool)
        new = np.cumsum(alive, dtype=np.int32)
        n, at, k = int(new[-1]) if len(new) else 0, 0, 0
        new -= 1
        new[~alive] = -1
        for first, size in self.parts:  # edges lie in the order of the parts, so what stays is moved to the front
            degree = self.degree[first : first + size]
            e = int(degree.sum())
            by = np.repeat(np.arange(size, dtype=np.int32), degree)
            on = (self.mask[at : at + e] & need != 0) & alive[first : first + size][by]
            to = new[self.dst[at : at + e][on]]
            self.dst[k : k + len(to)] = to
            self.degree[first : first + size] = np.bincount(by[on], minlength=size)
            at, k = at + e, k + len(to)
        self.mask = None
        self.dst.resize(k, refcheck=False)
        src, at = np.empty(k, np.int32), 0
        for first, size in self.parts:
            degree = self.degree[first : first + size]
            e = int(degree.sum())
            src[at : at + e] = np.repeat(new[first : first + size], degree)
            at += e
        self.degree = None
        return new, n, src, self.dst

    def ranks(self) -> np.ndarray:
        """Longest path from a vertex without in-edges; -1 on and behind cycles."""
        waits, rank, round_ = np.zeros(self.n, np.int32), np.full(self.n, -1, np.int32), 0
        for k in range(0, self.m, CHUNK):
            np.add.at(waits, self.dst[k : k + CHUNK], 1)
        front = np.flatnonzero(waits == 0)
        while len(front):
            rank[front] = round_
            free = []
            for e, _ in self.leaving(front):
                d = self.dst[e]
                np.subtract.at(waits, d, 1)
                free.append(np.unique(d[waits[d] == 0]))
            front, round_ = np.concatenate(free), round_ + 1
        return rank

    def grades(self, score: np.ndarray, start: np.ndarray, weights: np.ndarray, label: int, sources: np.ndarray, factors: np.ndarray) -> None:
        """Raise score to its fixpoint. weights: by label; edges of `label` are also weighed by their source's factor."""
        order = np.argsort(sources)
        sources, factors = np.append(sources[order], -1), np.append(factors[order], 1.0)
        front = np.unique(start)
        while len(front):
            rose = []
            for e, at in self.leaving(front):
                s, mask = score[front[at]], self.mask[e]
                w, of = weights[mask >> 2], front[at]
                here = np.flatnonzero(mask >> 2 == label)
                k = np.searchsorted(sources[:-1], of[here])
                w[here] *= np.where(sources[k] == of[here], factors[k], 1.0)
                v = np.where(s > 1, 1 + (s - 1) * w, s * w)
                on = (s > 1) | (mask & 1 != 0)
                d, v = self.dst[e[on]], _rounded(v[on])
                up = v > score[d]
                d, v = d[up], v[up]
                np.maximum.at(score, d, v)
                rose.append(d)
            front = np.unique(np.concatenate(rose))


def _rounded(x: np.ndarray) -> np.ndarray:
    """To nine digits, halves up, as Spark rounds the shortest decimals of doubles."""
    big = x * 1e9
    out = np.floor(big + 0.5) / 1e9
    close = np.flatnonzero(np.abs(big - np.floor(big) - 0.5) < 1e-4)
    if len(close):
        values, back = np.unique(x[close], return_inverse=True)
        exact = [float(Decimal(repr(float(v))).quantize(Decimal("1e-9"), ROUND_HALF_UP)) for v in values]
        out[close] = np.array(exact)[back]
    return out


def _in_one_task(at: Numbered, placed: DataFrame | None, work: Callable[[Whole, dict[int, tuple[np.ndarray, np.ndarray]]], np.ndarray]) -> DataFrame:
    """block, result: what work makes of all edges and the placed rows by kind, a value for each vertex, cut by block."""
    spark, offset, n, m = at.table.sparkSession, at.offset, at.n, at.m
    null = lambda *names: [F.lit(None).cast("binary").alias(x) for x in names]
    rows = at.table.select("block", "degree", "dst", "mask", F.lit(None).cast("int").alias("kind"), *null("numbers", "values"))
    if placed is not None:
        rows = rows.unionAll(placed.select(F.lit(None).cast("int").alias("block"), *null("degree", "dst", "mask"), "kind", "numbers", "values"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        whole, kinds = Whole(n, m), {}
        for b in batches:
            for i in range(b.num_rows):
                block, kind = b.column(0)[i].as_py(), b.column(4)[i].as_py()
                view = lambda k, t: np.frombuffer(b.column(k)[i].as_buffer(), t)  # noqa: B023, E731
                if kind is None:
                    whole.add(offset[block], view(1, np.int32), view(2, np.int32), view(3, np.int8))
                else:
                    kinds.setdefault(kind, []).append((view(5, np.int32).copy(), view(6, np.float64).copy()))
        both = {k: tuple(np.concatenate(x) for x in zip(*v, strict=True)) for k, v in kinds.items()}
        got = work(whole, both)
        starts = [*sorted(offset.items()), (None, n)]
        for (block, a), (_, z) in zip(starts, starts[1:], strict=False):
            yield pa.RecordBatch.from_arrays([pa.array([block], pa.int32()), pa.array([got[a:z].tobytes()], pa.binary())], names=["block", "result"])

    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    old = spark.conf.get(key)
    spark.conf.set(key, "4")  # a row is some megabytes
    try:
        return Staged(rows.coalesce(1).mapInArrow(run, "block int, result binary"), "gathered", "lz4").df
    finally:
        spark.conf.set(key, old)


def _named(blocks: Blocks, at: Numbered, result: DataFrame, kind: type, name: str, wanted: Callable[[np.ndarray], np.ndarray]) -> DataFrame:
    """vid and the result of the vertices wanted."""
    sql = {np.int8: "int", np.int32: "int", np.float64: "double"}[kind]
    to = {"int": np.int32, "double": np.float64}[sql]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                ids, got = np.frombuffer(b.column(0)[i].as_buffer(), np.int64), np.frombuffer(b.column(1)[i].as_buffer(), kind)
                on = np.flatnonzero(wanted(got))
                for k in range(0, len(on), 500_000):
                    x = on[k : k + 500_000]
                    yield pa.RecordBatch.from_arrays([pa.array(ids[x]), pa.array(got[x].astype(to))], names=["vid", name])

    met = at.table.select("block", "ids").join(result.repartition(blocks.n, "block").hint("shuffle_hash"), "block")
    return met.select("ids", "result").mapInArrow(run, f"vid long, {name} {sql}")


def solve(blocks: Blocks, masks: tuple[int, ...] | None, seeds: DataFrame, known: DataFrame | None = None) -> DataFrame:
    """As blocks.solve: vid, status of all that is not safe."""
    at = number(blocks)
    rows = lambda df, add: df.where("status > 0").select("vid", (F.col("status").cast("int") + add).alias("kind"), F.lit(0.0).alias("value"))
    all_ = rows(seeds, 0) if known is None else rows(seeds, 0).unionAll(rows(known, 2))
    placed = _placed(blocks, at, all_)

    def work(whole: Whole, kinds: dict) -> np.ndarray:
        whole.remask(masks)
        level, none = np.zeros(whole.n, np.int8), np.empty(0, np.int32)
        for kind in (3, 4):
            level[kinds.get(kind, (none,))[0]] = kind - 2
        for to in (2, 1):
            whole.settle(level, kinds.get(to, (none,))[0], to)
        return level

    got = _named(blocks, at, _in_one_task(at, placed, work), np.int8, "status", lambda x: x > 0)
    lost = placed.where(F.size("vids") > 0).select(F.explode("vids").alias("vid"), ((F.col("kind") - 1) % 2 + 1).alias("status"))
    return Staged(got.unionAll(lost.groupBy("vid").agg(F.max("status").alias("status"))), "status").df


def ranks(blocks: Blocks) -> DataFrame:
    """vid, level: longest path from a vertex without in-edges; null on and behind cycles."""
    at = number(blocks)
    got = _named(blocks, at, _in_one_task(at, None, lambda whole, _: whole.ranks()), np.int32, "level", lambda x: x >= -1)
    return got.select("vid", F.when(F.col("level") >= 0, F.col("level").cast("long")).alias("level"))


def grades(blocks: Blocks, scores: DataFrame, weights: list[float], label: int, factors: DataFrame) -> DataFrame:
    """vid, score, as extensions.propagate_scored. weights: by label's place; factors: vid, factor of sources of edges
    of the label at place `label`."""
    at = number(blocks)
    rows = scores.groupBy("vid").agg(F.max(F.col("score").cast("double")).alias("value")).select("vid", F.lit(1).alias("kind"), "value")
    placed = _placed(blocks, at, rows.unionAll(factors.select("vid", F.lit(2).alias("kind"), F.col("factor").cast("double").alias("value"))))

    def work(whole: Whole, kinds: dict) -> np.ndarray:
        score, none = np.full(whole.n, -1.0), (np.empty(0, np.int32), np.empty(0))
        start, value = kinds.get(1, none)
        score[start] = value
        sources, factor = kinds.get(2, none)
        whole.grades(score, start, np.append(np.array(weights), 1.0), label, sources, factor)
        return score

    return _named(blocks, at, _in_one_task(at, placed, work), np.float64, "score", lambda x: x >= 0)


# --- which of many starts reach how many products, and how many starts reach each target -------

#: Edges of a shrunk graph up to which every task holds it, and in-edges of a vertex that are taken one by one.
SPREAD_CAP, SLOTS = 30_000_000, 64


def _tasks(spark: SparkSession) -> int:
    """Tasks that hold a graph each: no more than run at once."""
    return max(1, min(partitions(spark), spark.sparkContext.defaultParallelism))


def _few_at_a_time(make: Callable[[], DataFrame], spark: SparkSession) -> DataFrame:
    """make() with few rows in an Arrow batch, since a row is some megabytes."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    old = spark.conf.get(key)
    spark.conf.set(key, "4")
    try:
        return make()
    finally:
        spark.conf.set(key, old)


def _shrinking(at: Numbered, placed: DataFrame, masks: tuple[int, ...] | None, work: Callable[[Whole, dict[int, tuple[np.ndarray, np.ndarray]]], Iterator[tuple[int, dict[str, np.ndarray]]]], name: str) -> DataFrame:
    """part and pieces of the arrays that work makes of all edges and the placed rows by kind, in one task."""
    spark, offset, n, m = at.table.sparkSession, at.offset, at.n, at.m
    null = lambda *names: [F.lit(None).cast("binary").alias(x) for x in names]
    rows = at.table.select("block", "degree", "dst", "mask", F.lit(None).cast("int").alias("kind"), *null("numbers", "values"))
    rows = rows.unionAll(placed.select(F.lit(None).cast("int").alias("block"), *null("degree", "dst", "mask"), "kind", "numbers", "values"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        whole, kinds = Whole(n, m), {}
        for b in batches:
            for i in range(b.num_rows):
                block, kind = b.column(0)[i].as_py(), b.column(4)[i].as_py()
                view = lambda k, t: np.frombuffer(b.column(k)[i].as_buffer(), t)  # noqa: B023, E731
                if kind is None:
                    whole.add(offset[block], view(1, np.int32), view(2, np.int32), view(3, np.int8))
                else:
                    kinds.setdefault(kind, []).append((view(5, np.int32).copy(), view(6, np.float64)[: None if kind else 0].copy()))  # kind 0 has no values
        b = None
        both = {k: tuple(np.concatenate(x) for x in zip(*v, strict=True)) for k, v in kinds.items()}
        kinds.clear()
        whole.remask(masks)
        for part, arrays in work(whole, both):
            for piece in shrunk.pieces(**arrays):
                yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), *piece.columns], names=["part", *piece.schema.names])

    return _few_at_a_time(lambda: Staged(rows.coalesce(1).mapInArrow(run, "part int, " + shrunk.PIECES), name, "lz4").df, spark)


def _in_every_task(graph: DataFrame, work: Callable[[dict[int, dict[str, np.ndarray]], int, int], Iterator[pa.RecordBatch]], schema: str, name: str) -> DataFrame:
    """What work makes of the parts' arrays, the task and the number of tasks, in each of them."""
    spark, tasks = graph.sparkSession, _tasks(graph.sparkSession)
    each = F.explode(F.sequence(F.lit(0), F.lit(tasks - 1))).alias("task")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, task = {}, None
        for b in batches:
            for i in range(b.num_rows):
                task = b.column(0)[i].as_py()
                parts.setdefault(b.column(1)[i].as_py(), shrunk.Joined()).add(b, i, 2)
        if task is not None:
            yield from work({k: x.arrays for k, x in parts.items()}, task, tasks)

    dealt = graph.select(each, "*").repartitionById(tasks, F.col("task"))
    return _few_at_a_time(lambda: Staged(dealt.mapInArrow(run, schema), name, "lz4").df, spark)


def _folded(new: np.ndarray, n: int, src: np.ndarray, dst: np.ndarray, keep: np.ndarray, *more: np.ndarray) -> tuple[int, np.ndarray, np.ndarray, list[np.ndarray]]:
    """What is not kept and has one out-edge is merged into that edge's end; how many vertices are left, their edges, and
    where the kept ones and more (both by old numbers) are: -1 if not reached."""
    flag = np.zeros(n, bool)
    flag[new[keep[new[keep] >= 0]]] = True
    to, m = shrunk.ends(n, src, dst, flag), 0
    flag[:] = False
    for k in range(0, len(src), CHUNK):  # what stays is moved to the front
        s, d = src[k : k + CHUNK], to[dst[k : k + CHUNK]]
        on = (to[s] == s) & (s != d)
        s, d = s[on], d[on]
        flag[s], flag[d] = True, True
        src[m : m + len(s)], dst[m : m + len(s)] = s, d
        m += len(s)
    src.resize(m, refcheck=False)
    dst.resize(m, refcheck=False)
    places = [np.where(new[x] >= 0, to[new[x]], np.int32(-1)) for x in (keep, *more)]
    to = None
    for p in places:
        flag[p[p >= 0]] = True
    at = np.cumsum(flag, dtype=np.int32)
    at -= 1
    for x in (src, dst):
        for k in range(0, m, CHUNK):
            x[k : k + CHUNK] = at[x[k : k + CHUNK]]
    return int(flag.sum()), src, dst, [np.where(p >= 0, at[p], np.int32(-1)) for p in places]


def reach_counts(blocks: Blocks, masks: tuple[int, ...] | None, starts: DataFrame, products: DataFrame) -> DataFrame | None:
    """start (its number) and n: how many products (vid) it reaches. starts: number, vid, need, of one need each.
    One task shrinks the graph, every task sweeps a share of the starts. None if what is left is too large."""
    at = number(blocks)
    rows = starts.select("vid", F.col("need").cast("int").alias("kind"), F.col("number").cast("double").alias("value"))
    rows = rows.unionAll(products.select("vid").distinct().select("vid", F.lit(0).alias("kind"), F.lit(0.0).alias("value")))
    placed = _placed(blocks, at, rows)
    if placed.where("kind > 0 and size(vids) > 0").limit(1).count():
        raise ValueError("a start is no vertex")

    def shrink(whole: Whole, kinds: dict) -> Iterator[tuple[int, dict[str, np.ndarray]]]:
        wanted = kinds.pop(0, (np.empty(0, np.int32),))[0]
        for k, need in enumerate(sorted(kinds)):
            place, value = kinds[need]
            one = whole if k == len(kinds) - 1 else deepcopy(whole)
            new, n, src, dst = one.reached(place, need)
            one = None
            n, src, dst, (products_, place) = _folded(new, n, src, dst, wanted, place)
            new = None
            names, which = np.unique(value, return_inverse=True)
            several = np.bincount(which) > 1  # starts that begin in several places are vertices of their own
            own, spread = n + np.cumsum(several) - 1, several[which]
            edges = [np.concatenate([src, own[which[spread]]], dtype=np.int32) if spread.any() else src]
            src = None
            edges.append(np.concatenate([dst, place[spread]], dtype=np.int32) if spread.any() else dst)
            dst, begin = None, own
            begin[which[~spread]] = place[~spread]
            graph, begin = shrunk.shrink_back(n + int(several.sum()), edges, products_[products_ >= 0], begin)
            yield need, {**graph, "number": names.astype(np.int64), "which": begin}

    small = _shrinking(at, placed, masks, shrink, "shrunk")
    if (small.where("name = 'src'").agg(F.max("size")).first()[0] or 0) > SPREAD_CAP:
        return None

    def sweep(parts: dict[int, dict[str, np.ndarray]], task: int, tasks: int) -> Iterator[pa.RecordBatch]:
        for need, graph in parts.items():
            order = np.argsort(graph["which"], kind="stable")
            sorted_ = graph["which"][order]
            for mine, counts in shrunk.reaches(graph, task, tasks, SLOTS):
                a, z = np.searchsorted(sorted_, mine), np.searchsorted(sorted_, mine, "right")
                rows = np.concatenate([order[i:j] for i, j in zip(a, z, strict=True)])
                yield pa.RecordBatch.from_arrays([pa.array(graph["number"][rows]), pa.array(np.repeat(counts, z - a))], names=["number", "n"])

    return _in_every_task(small, sweep, "number long, n long", "counts")


def reach_hops(blocks: Blocks, masks: tuple[int, ...] | None, starts: DataFrame) -> DataFrame | None:
    """number, n, hops of starts (number, vid, need; each a vertex): how many vertices each reaches and in how many hops
    at most. None if there are cycles or what is left of the graph is too large."""
    at = number(blocks)
    placed = _placed(blocks, at, starts.select("vid", F.col("need").cast("int").alias("kind"), F.col("number").cast("double").alias("value")))
    if placed.where("size(vids) > 0").limit(1).count():
        raise ValueError("a start is no vertex")

    def shrink(whole: Whole, kinds: dict) -> Iterator[tuple[int, dict[str, np.ndarray]]]:
        for k, need in enumerate(sorted(kinds)):
            place, value = kinds[need]
            one = whole if k == len(kinds) - 1 else deepcopy(whole)
            new, n, src, dst = one.reached(place, need)
            one, place = None, new[place]
            new = None
            graph = shrunk.shrink_hops(n, src, dst, place)
            yield need, {"cyclic": np.zeros(1)} if graph is None else {**graph, "number": value.astype(np.int64)}

    small = _shrinking(at, placed, masks, shrink, "shrunk")
    if small.where(f"name = 'cyclic' or (name = 'src' and size > {SPREAD_CAP})").limit(1).count():
        return None

    def sweep(parts: dict[int, dict[str, np.ndarray]], task: int, tasks: int) -> Iterator[pa.RecordBatch]:
        for graph in parts.values():
            for first, n, deepest in shrunk.hops(graph, task, tasks, SLOTS):
                yield pa.RecordBatch.from_arrays([pa.array(graph["number"][first : first + len(n)]), pa.array(n), pa.array(deepest)], names=["number", "n", "hops"])

    return _in_every_task(small, sweep, "number long, n long, hops long", "hops")


def class_counts(blocks: Blocks, masks: tuple[int, ...] | None, members: DataFrame, targets: DataFrame) -> DataFrame:
    """As exposure.class_counts, of edges that the greatest level passes."""
    at = number(blocks)
    spark, offset = at.table.sparkSession, at.offset
    members = Staged(members.select("start", "cls", "vid"), "members").df
    classes = sorted(r["cls"] for r in members.select("cls").distinct().collect())
    if not classes:
        return spark.createDataFrame([], "vid long, cls string, n long")
    numbers = Staged(members.select("start", "cls").distinct().withColumn("value", F.monotonically_increasing_id().cast("double")), "members").df
    code = F.array_position(F.array(*[F.lit(x) for x in classes]), F.col("cls")).cast("int").alias("kind")
    rows = members.join(numbers, ["start", "cls"]).select("vid", code, "value")
    placed = _placed(blocks, at, rows.unionAll(targets.select("vid").distinct().select("vid", F.lit(0).alias("kind"), F.lit(0.0).alias("value"))))

    def shrink(whole: Whole, kinds: dict) -> Iterator[tuple[int, dict[str, np.ndarray]]]:
        wanted = np.sort(kinds.pop(0, (np.empty(0, np.int32),))[0])
        place, value = (np.concatenate([kinds[k][i] for k in kinds] or [np.empty(0, np.int32)]) for i in (0, 1))
        cls = np.concatenate([np.full(len(kinds[k][0]), k - 1, np.int8) for k in kinds] or [np.empty(0, np.int8)])
        kinds.clear()
        new, n, src, dst = whole.reached(place, 2)
        n, src, dst, (target, place) = _folded(new, n, src, dst, wanted, place)
        new = None
        wanted, target = wanted[target >= 0], target[target >= 0]
        graph, name = shrunk.shrink(n, src, dst, value.astype(np.int64), cls, place, len(classes), target)
        yield 0, graph
        yield 1, {"wanted": wanted, "name": name}

    small = _shrinking(at, placed, masks, shrink, "shrunk")

    def sweep(parts: dict[int, dict[str, np.ndarray]], task: int, tasks: int) -> Iterator[pa.RecordBatch]:
        total = shrunk.sweeps(parts[0], task, tasks)
        yield from shrunk.pieces(total=total.astype(np.int32) if total.max(initial=0) < 1 << 31 else total)

    swept = _in_every_task(small.where("part = 0"), sweep, shrunk.PIECES, "swept")
    n_cls, ends = len(classes), sorted(offset.items(), key=lambda x: x[1])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, names = shrunk.Joined(), shrunk.Joined()
        for b in batches:
            for i in range(b.num_rows):
                total = b.column(0)[i].as_py() == "total"
                (sums if total else names).add(b, i, 0, total)
        wanted, name, total = names.arrays["wanted"], names.arrays["name"], sums.arrays["total"]
        for (block, a), z in zip(ends, [*[x for _, x in ends[1:]], None], strict=True):
            i, j = np.searchsorted(wanted, a), len(wanted) if z is None else np.searchsorted(wanted, z)
            for k in range(n_cls):
                n = total[name[i:j], k]
                on = np.flatnonzero(n)
                yield pa.RecordBatch.from_arrays([pa.array([block], pa.int32()), pa.array([k], pa.int32()), pa.array([(wanted[i:j][on] - a).astype(np.int32).tobytes()], pa.binary()), pa.array([n[on].tobytes()], pa.binary())], names=["block", "k", "numbers", "n"])

    parts = swept.unionAll(small.where("part = 1").drop("part")).coalesce(1)
    added = _few_at_a_time(lambda: Staged(parts.mapInArrow(add, "block int, k int, numbers binary, n binary"), "class-counts", "lz4").df, spark)

    def named(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                ids, numbers, n = (np.frombuffer(b.column(c)[i].as_buffer(), t) for c, t in ((0, np.int64), (2, np.int32), (3, np.int64)))
                for k in range(0, len(n), 500_000):
                    x = ids[numbers[k : k + 500_000]]
                    yield pa.RecordBatch.from_arrays([pa.array(x), pa.array([classes[b.column(1)[i].as_py()]] * len(x), pa.string()), pa.array(n[k : k + 500_000])], names=["vid", "cls", "n"])

    met = at.table.select("block", "ids").join(added.repartition(blocks.n, "block").hint("shuffle_hash"), "block").select("ids", "k", "numbers", "n")
    counted = met.mapInArrow(named, "vid long, cls string, n long")
    lost = placed.where("kind = 0 and size(vids) > 0").select(F.explode("vids").alias("vid"))  # no edge touches them
    return counted.unionAll(members.distinct().join(lost, "vid").groupBy("vid", "cls").agg(F.count("*").alias("n")))
