"""Status of graphs of any size, block by block.

Vertices are dealt to blocks of bounded size; a block holds the out-edges of its vertices and, as
stubs, the far ends that live elsewhere. Each round every block that was sent something is settled
by array kernels to its own fixpoint, and only stubs that rose are sent to the blocks that own them.
Blocks are laid out once, in files bucketed by block, so a round moves levels and messages alone.
"""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from supplyrisk.operators.kernels import Csr
from supplyrisk.plans.staging import Staged, partitions, shared_dir

#: Edges a block holds on average.
BLOCK_EDGES = 1_000_000
ROWS = "block int, kind int, vids array<bigint>, state binary"


@dataclass
class Blocks:
    """table: block, blob, own (vertices of the block); bucketed by block into `n` buckets. block_of: the block of a vertex id."""

    table: DataFrame
    n: int
    home: Callable[[Column], Column] | None = None
    #: Made by operators/gathered.py when it is first asked for.
    numbered: object = None

    def block_of(self, vid: Column) -> Column:
        return block_of(vid, self.n, self.home)


def block_of(vid: Column, n: int, home: Callable[[Column], Column] | None = None) -> Column:
    return F.pmod(F.xxhash64(home(vid) if home is not None else vid), F.lit(n)).cast("int")


def lay_out(prop: DataFrame, vertices: DataFrame, labels: tuple[str, ...], n_edges: int, home: Callable[[Column], Column] | None = None) -> Blocks:
    """home: what of an id to deal by, so that vertices that hand on to each other share a block."""
    spark = prop.sparkSession
    n = max(partitions(spark), -(-n_edges // BLOCK_EDGES))
    code = F.coalesce(F.array_position(F.array(*[F.lit(x) for x in labels]), F.col("label")) - 1, F.lit(len(labels))) if "label" in prop.columns else F.lit(len(labels))
    edges = prop.select(block_of(F.col("src"), n, home).alias("block"), "src", "dst", (F.col("mask") + code * 4).cast("int").alias("mask"), block_of(F.col("dst"), n, home).alias("far"))
    none = F.lit(None)
    alone = vertices.select(block_of(F.col("vid"), n, home).alias("block"), F.col("vid").alias("src"), none.cast("long").alias("dst"), none.cast("int").alias("mask"), none.cast("int").alias("far"))
    every = spark.range(n).select(F.col("id").cast("int").alias("block"), none.cast("long").alias("src"), none.cast("long").alias("dst"), none.cast("int").alias("mask"), none.cast("int").alias("far"))  # so no block is missing
    rows = edges.unionAll(alone).unionAll(every).repartitionById(n, F.col("block"))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got, alone_, block = [], [], None
        for b in batches:
            if not b.num_rows:
                continue
            block = b.column(0)[0].as_py()
            edge = b.column(2).is_valid().to_numpy(zero_copy_only=False)
            alone_.append(b.column(1).filter(pc.and_not(b.column(1).is_valid(), pa.array(edge))).to_numpy(zero_copy_only=False))
            b = b.filter(pa.array(edge))
            got.append([b.column(i).to_numpy(zero_copy_only=False) for i in (1, 2, 3, 4)])
        if block is None:
            return
        src, dst, mask, far = (np.concatenate([g[i] for g in got]) for i in range(4))
        csr = Csr(src, dst, mask, np.concatenate(alone_))
        owner = np.full(len(csr.ids), block, np.int32)
        owner[csr.number(dst)] = far
        yield pa.RecordBatch.from_arrays([pa.array([block], pa.int32()), pa.array([csr.packed() + owner.tobytes()], pa.large_binary()), pa.array([int((owner == block).sum())], pa.int32())], names=["block", "blob", "own"])

    return Blocks(bucketed(rows.mapInArrow(pack, "block int, blob binary, own int"), n, "blocks"), n, home)


def bucketed(df: DataFrame, n: int, label: str) -> DataFrame:
    """df as a table in n buckets of `block`, in the shared folder."""
    spark, name = df.sparkSession, f"{label}_{uuid.uuid4().hex}"
    writer = df.repartition(n, "block").write.format("parquet").option("compression", "lz4").option("path", f"{shared_dir(spark)}/staged-{name}")
    writer.bucketBy(n, "block").saveAsTable(name)
    return spark.table(name)


def _settle(csr: Csr, level: np.ndarray, start: np.ndarray, to: int) -> None:
    """Raise start to a level and send it on inside the block."""
    need = 2 if to == 2 else 1
    new = np.unique(start[level[start] < to])
    while len(new):
        level[new] = to
        e = csr.out(new)
        d = csr.dst[e[csr.mask[e] & need != 0]]
        new = np.unique(d[level[d] < to])


def _round(masks: tuple[int, ...] | None):
    """block, blob, parts -> rows of ROWS: kind 0 a block's levels, 1 and 2 vertices sent at that level,
    3 and 4 vertices known to be at level 1 and 2 that send nothing (in, first round only)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                block, blob, parts = b.column(0)[i].as_py(), b.column(1)[i], b.column(2)[i].values
                kinds = parts.field("kind").to_numpy(zero_copy_only=False)
                vids, states = parts.field("vids"), parts.field("state")
                old = [states[int(k)].as_buffer() for k in np.flatnonzero(kinds == 0)]
                if not blob.is_valid:
                    yield _rows([(block, 0, None, old[0].to_pybytes())])
                    continue
                buffer = blob.as_buffer()
                csr = Csr.unpacked(buffer).remasked(masks)
                n = len(csr.ids)
                owner = np.frombuffer(buffer, np.int32, n, buffer.size - 4 * n)
                level = np.frombuffer(old[0], np.int8, n).copy() if old else np.zeros(n, np.int8)
                lost = []

                def of(kind: int) -> np.ndarray:
                    got = [vids[int(k)].values.to_numpy(zero_copy_only=False) for k in np.flatnonzero(kinds == kind)]
                    ids = np.concatenate(got) if got else np.empty(0, np.int64)
                    at = np.minimum(np.searchsorted(csr.ids, ids), max(n - 1, 0))
                    inside = csr.ids[at] == ids if n else np.zeros(len(ids), bool)
                    lost.append(((kind - 1) % 2 + 1, ids[~inside]))
                    return at[inside]

                for kind in (3, 4):
                    at = of(kind)
                    level[at] = np.maximum(level[at], kind - 2)
                before = level.copy()
                _settle(csr, level, of(2), 2)
                _settle(csr, level, of(1), 1)
                out = [(block, 0, None, level.tobytes())]
                for to in (1, 2):
                    rose = np.flatnonzero((level == to) & (before < to) & (owner != block))
                    rose = rose[np.argsort(owner[rose], kind="stable")]
                    where, first = np.unique(owner[rose], return_index=True)
                    out += [(int(w), to, x, None) for w, x in zip(where, np.split(csr.ids[rose], first[1:]) if len(rose) else [], strict=True)]
                out += [(block, -to, x, None) for to, x in lost if len(x)]  # no edge and no known vertex: it keeps its level
                yield _rows(out)

    return run


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    block, kind, vids, state = zip(*rows, strict=True)
    sizes = np.array([0 if v is None else len(v) for v in vids])
    flat = np.concatenate([v for v in vids if v is not None] or [np.empty(0, np.int64)])
    lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)), pa.array(flat, pa.int64()))
    return pa.RecordBatch.from_arrays([pa.array(block, pa.int32()), pa.array(kind, pa.int32()), lists, pa.array(state, pa.binary())], names=["block", "kind", "vids", "state"])


def _listed(blocks: Blocks, state: DataFrame, add: int) -> DataFrame:
    none = F.lit(None).cast("binary").alias("state")
    return state.where("status > 0").groupBy(blocks.block_of(F.col("vid")).alias("block"), (F.col("status").cast("int") + add).alias("kind")).agg(F.collect_list("vid").alias("vids")).select("block", "kind", "vids", none)


def solve(blocks: Blocks, masks: tuple[int, ...] | None, seeds: DataFrame, known: DataFrame | None = None, max_rounds: int = 10_000, log: object = None) -> DataFrame:
    """vid, status of all that is not safe. known: a state to start from; only what rises above it is sent."""
    sent, lost, size = _listed(blocks, seeds, 0), None, 1
    if known is not None:
        sent = sent.unionAll(_listed(blocks, known, 2))
    before = None
    for _ in range(max_rounds):
        began, seen = time.time(), Observation()
        parts = sent.repartition(blocks.n, "block").groupBy("block").agg(F.collect_list(F.struct("kind", "vids", "state")).alias("parts"))
        fed = F.exists("parts", lambda x: x["kind"] != 0)
        dealt = blocks.table.join(parts.hint("shuffle_hash"), "block").select("block", F.when(fed, F.col("blob")).alias("blob"), "parts")
        n_sent = F.sum(F.when(F.col("kind") > 0, F.size("vids")))
        step = Staged(dealt.mapInArrow(_round(masks), ROWS).observe(seen, F.coalesce(n_sent, F.lit(0)).alias("sent"), F.count_if(F.col("kind") < 0).alias("lost")), "round", "lz4")
        if seen.get["lost"]:
            more = Staged(step.df.where("kind < 0").select(F.explode("vids").alias("vid"), (-F.col("kind")).alias("status")), "lost").df
            lost = more if lost is None else lost.unionAll(more)
        if before is not None:
            before.drop()
        before, sent, size = step, step.df.where("kind >= 0"), seen.get["sent"]
        if log is not None:
            log.add(frontier=size, messages=size, raised=size, seconds=time.time() - began)
        if not size:
            break
    else:
        raise RuntimeError(f"no fixpoint after {max_rounds} rounds")
    state = sent.where("kind = 0").repartition(blocks.n, "block").select("block", F.col("state").alias("levels"))

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                block, buffer = b.column(0)[i].as_py(), b.column(1)[i].as_buffer()
                csr = Csr.unpacked(buffer)
                n = len(csr.ids)
                level = np.frombuffer(b.column(2)[i].as_buffer(), np.int8, n)
                on = np.flatnonzero((level > 0) & (np.frombuffer(buffer, np.int32, n, buffer.size - 4 * n) == block))
                for k in range(0, len(on), 500_000):
                    at = on[k : k + 500_000]
                    yield pa.RecordBatch.from_arrays([pa.array(csr.ids[at]), pa.array(level[at].astype(np.int32))], names=["vid", "status"])

    got = blocks.table.join(state.hint("shuffle_hash"), "block").select("block", "blob", "levels").mapInArrow(read, "vid long, status int")
    if lost is not None:
        got = got.unionAll(lost.groupBy("vid").agg(F.max("status").alias("status")))
    return Staged(got, "status").df


# --- which of many starts reach what --------------------------------------------------------

#: Words of 64 starts that go together.
WORDS = 4


def _or_by(at: np.ndarray, bits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct places, each with the bits of all its rows."""
    order = np.argsort(at, kind="stable")
    at, first = np.unique(at[order], return_index=True)
    return at, np.bitwise_or.reduceat(bits[order], first, axis=0) if len(at) else bits[:0]


def _spread_round(masks: tuple[int, ...] | None, allowed: np.ndarray, by_hop: bool):
    """As _round, with a row of words for each vertex. Messages (kind 1) carry words in `state`. by_hop:
    one hop a round. Kind 9: how many vertices each start newly reached."""
    words = allowed.shape[1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                block, blob, parts = b.column(0)[i].as_py(), b.column(1)[i], b.column(2)[i].values
                kinds = parts.field("kind").to_numpy(zero_copy_only=False)
                vids, states = parts.field("vids"), parts.field("state")
                old = [states[int(k)].as_buffer() for k in np.flatnonzero(kinds == 0)]
                if not blob.is_valid:
                    yield _rows([(block, 0, None, old[0].to_pybytes())])
                    continue
                buffer = blob.as_buffer()
                csr = Csr.unpacked(buffer).remasked(masks)
                n = len(csr.ids)
                owner = np.frombuffer(buffer, np.int32, n, buffer.size - 4 * n)
                held = np.frombuffer(old[0], np.uint64).reshape(n, words).copy() if old else np.zeros((n, words), np.uint64)
                got = np.flatnonzero(kinds == 1)
                ids = np.concatenate([vids[int(k)].values.to_numpy(zero_copy_only=False) for k in got])
                bits = np.concatenate([np.frombuffer(states[int(k)].as_buffer(), np.uint64).reshape(-1, words) for k in got])
                at = csr.number(ids)
                if len(ids) and (at.max() >= n or (csr.ids[at] != ids).any()):
                    raise ValueError("an edge ends at a vertex that does not exist")
                front, fresh = _or_by(at, bits)
                fresh = fresh & ~held[front]
                held[front] |= fresh
                counts = np.unpackbits(fresh.view(np.uint8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64) if by_hop else None
                to, sent = [], []
                while len(front):
                    on = fresh.any(axis=1)
                    front, fresh = front[on], fresh[on]
                    e = csr.out(front)
                    given = np.repeat(fresh, csr.start[front + 1] - csr.start[front], axis=0) & allowed[csr.mask[e]]
                    d = csr.dst[e]
                    given &= ~held[d]
                    on = given.any(axis=1)
                    front, fresh = _or_by(d[on], given[on])
                    away = owner[front] != block
                    held[front[away]] |= fresh[away]
                    leaves = np.ones(len(front), bool) if by_hop else away
                    to.append(front[leaves])
                    sent.append(fresh[leaves])
                    if by_hop:
                        break
                    held[front] |= fresh
                out = [(block, 0, None, held.tobytes())]
                if to:
                    place, send = _or_by(np.concatenate(to), np.concatenate(sent))
                    order = np.argsort(owner[place], kind="stable")
                    place, send = place[order], send[order]
                    where, first = np.unique(owner[place], return_index=True)
                    for w, a, z in zip(where, first, [*first[1:], len(place)][: len(first)], strict=True):
                        out.append((int(w), 1, csr.ids[place[a:z]], send[a:z].tobytes()))
                if by_hop:
                    out.append((block, 9, counts, None))
                yield _rows(out)

    return run


def spread(blocks: Blocks, masks: tuple[int, ...] | None, starts: DataFrame, max_rounds: int = 10_000, by_hop: bool = False) -> DataFrame:
    """block, need, vid, bits of all that starts reach. starts: block (of up to 64), bit, need, vid; every vid is a
    vertex or the source of an edge. by_hop: block, bit, n, hops instead: how many vertices, in how many hops."""
    spark = starts.sparkSession
    shares = starts.groupBy("block", "need").agg(F.bit_or(F.expr("shiftleft(1L, bit)")).alias("of")).orderBy("block", "need").collect()  # a row for 64 starts
    numbers = sorted({r["block"] for r in shares})
    out, totals = None, []
    for k in range(0, len(numbers), WORDS):
        word = {x: i for i, x in enumerate(numbers[k : k + WORDS])}
        allowed = np.zeros((4, len(word)), np.uint64)
        for r in shares:
            if r["block"] in word:
                for mask in range(4):
                    if mask & r["need"]:
                        allowed[mask, word[r["block"]]] |= np.uint64(r["of"] & (2**64 - 1))
        mine = starts.where(F.col("block").isin(list(word)))
        lanes = [F.bit_or(F.when(F.col("block") == x, F.expr("shiftleft(1L, bit)")).otherwise(F.lit(0).cast("long"))) for x in word]
        raw = F.concat(*[_little(x) for x in lanes])
        begin = mine.groupBy("vid").agg(raw.alias("state")).select(blocks.block_of(F.col("vid")).alias("block"), F.lit(1).alias("kind"), F.array("vid").alias("vids"), "state")
        sent, before = begin, None
        for round_ in range(max_rounds):
            seen = Observation()
            parts = sent.repartition(blocks.n, "block").groupBy("block").agg(F.collect_list(F.struct("kind", "vids", "state")).alias("parts"))
            dealt = blocks.table.join(parts.hint("shuffle_hash"), "block").select("block", F.when(F.exists("parts", lambda x: x["kind"] != 0), F.col("blob")).alias("blob"), "parts")
            step = Staged(dealt.mapInArrow(_spread_round(masks, allowed, by_hop), ROWS).observe(seen, F.count_if(F.col("kind") == 1).alias("sent")), "spread", "lz4")
            if by_hop:
                for row in step.df.where("kind = 9").select(F.posexplode("vids").alias("at", "n")).groupBy("at").agg(F.sum("n").alias("n")).where("n > 0").collect():
                    totals.append((numbers[k + row["at"] // 64], row["at"] % 64, row["n"], round_))
            if before is not None:
                before.drop()
            before, sent = step, step.df.where("kind < 9")
            if not seen.get["sent"]:
                break
        else:
            raise RuntimeError(f"no fixpoint after {max_rounds} rounds")
        if by_hop:
            continue
        state = sent.where("kind = 0").repartition(blocks.n, "block").select("block", F.col("state").alias("held"))
        got = blocks.table.join(state.hint("shuffle_hash"), "block").select("block", "blob", "held").mapInArrow(_held(list(word)), "block long, vid long, bits long")
        part = Staged(got, "spread").df
        out = part if out is None else out.unionAll(part)
    if by_hop:
        rows = spark.createDataFrame(totals, "block long, bit int, n long, hops long")
        return rows.groupBy("block", "bit").agg(F.sum("n").alias("n"), F.max("hops").alias("hops"))
    if out is None:
        return spark.createDataFrame([], "block long, need int, vid long, bits long")
    of = spark.createDataFrame([(r["block"], r["need"], r["of"]) for r in shares], "block long, need int, of long")
    return out.join(F.broadcast(of), "block").select("block", "need", "vid", F.col("bits").bitwiseAND(F.col("of")).alias("bits")).where("bits <> 0")


def _little(x: Column) -> Column:
    """The eight bytes of a word, least first, as arrays have them."""
    return F.concat(*[F.substring(F.unhex(F.lpad(F.hex(x), 16, "0")), k, 1) for k in range(8, 0, -1)])


def _held(numbers: list[int]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                block, buffer = b.column(0)[i].as_py(), b.column(1)[i].as_buffer()
                csr = Csr.unpacked(buffer)
                n = len(csr.ids)
                held = np.frombuffer(b.column(2)[i].as_buffer(), np.uint64).reshape(n, len(numbers))
                mine = np.frombuffer(buffer, np.int32, n, buffer.size - 4 * n) == block
                for w, number in enumerate(numbers):
                    on = np.flatnonzero(mine & (held[:, w] != 0))
                    for k in range(0, len(on), 500_000):
                        at = on[k : k + 500_000]
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), number, np.int64)), pa.array(csr.ids[at]), pa.array(np.ascontiguousarray(held[at, w]).view(np.int64))], names=["block", "vid", "bits"])

    return run
