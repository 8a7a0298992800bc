"""Exact substring dedup: bytes of 50-byte strings that start in an earlier document.

A suffix order to depth 50 decides which strings are equal. It is not built over all
suffixes at once: positions are first put in buckets by a q-gram, and only buckets that can
still matter are refined, by sorting on the bucket identifiers of later offsets.

1. Documents are packed into blocks (about 4 MB; a row, so never split between tasks).
2. In each 50-byte window the least-hashed 24-gram is its anchor; windows of one anchor
   are neighbours and form a run of at most 27. The anchor is the q-gram bucket. Each block
   names its distinct anchors once; an anchor that only one document has is dropped (equal
   windows have equal anchors, so nothing is lost; equal hashes only keep more).
3. Runs of the anchors left send their bytes (76 at most), once per distinct run and block,
   to the anchor's task. There buckets are refined on bytes: the identifier of depth 24 is
   the anchor's, the next depths come from sorting on (identifier, byte at the later
   offset) to both sides, and a window's from the identifiers of its two sides. Buckets
   without a second member leave. The least document of each bucket of depth 50 decides.
4. Answers go back to the blocks that asked, and each document is cut.

Hashes only deal and drop; every match is decided on bytes. Within a block, runs that equal
an earlier document's byte for byte are removed without asking. Tasks work on slices of
about SLICE runs, cut between anchors. An anchor with more than HOT_RUNS runs is not put in
one task: its windows are grouped by Spark, with partial minima before the shuffle. Work
and shuffled bytes are proportional to the input.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from supplyrisk.llm.common import NULL_KEY, Staged, partitions

WIDTH = 50
GRAM = 24
SPAN = WIDTH - GRAM + 1
BLOCK_BYTES = 4 << 20
#: Entries that one bucket should get.
BUCKET_ENTRIES = 2_000_000
#: Bytes of windows worked on at once.
SEGMENT = 1 << 19
#: Runs refined at once in a task.
SLICE = 50_000
#: Runs of one anchor beyond which its windows are grouped by Spark instead of one task.
HOT_RUNS = 100_000

_U = np.uint64


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, _U)
    out[0] = 1
    return np.cumprod(out, dtype=_U)


_BASE = 0x9E3779B97F4A7C15 | 1
_BYTE = np.random.Generator(np.random.PCG64(50)).integers(0, 2**64, 256, dtype=_U)
_tables: dict[str, np.ndarray] = {}


def _power_tables() -> tuple[np.ndarray, np.ndarray]:
    if not _tables:
        n = SEGMENT + WIDTH + 1
        _tables["up"], _tables["down"] = _powers(_BASE, n), _powers(pow(_BASE, -1, 2**64), n)
    return _tables["up"], _tables["down"]


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> _U(31))) * _U(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> _U(27))) * _U(0x94D049BB133111EB)
    return h ^ (h >> _U(31))


class Runs:
    """Window runs of one block: first and last window start, document, anchor and its hash, run hash."""

    def __init__(self, data: np.ndarray, lens: np.ndarray):
        ends = np.cumsum(lens)
        starts = ends - lens
        parts = []
        for at in range(0, len(data), SEGMENT):
            if got := self._segment(data, starts, ends, at):
                parts.append(got)
        none = (np.empty(0, np.int64),) * 4 + (np.empty(0, _U),) * 2
        self.first, self.last, self.doc, self.anchor, self.gram, self.whole = (np.concatenate(x) for x in zip(*parts, strict=True)) if parts else none

    @staticmethod
    def _segment(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, at: int) -> tuple | None:
        d = data[at : at + SEGMENT + WIDTH - 1]
        lo = np.maximum(starts, at)
        count = np.maximum(np.minimum(ends - WIDTH + 1, at + SEGMENT) - lo, 0)
        total = int(count.sum())
        if not total:
            return None
        up, down = _power_tables()
        n = len(d)
        prefix = np.zeros(n + 1, _U)
        np.cumsum(_BYTE[d] * up[:n], out=prefix[1:])
        gram = _mix((prefix[GRAM:] - prefix[:-GRAM]) * down[: n - GRAM + 1])
        least = (gram & _U(0xFFFFFFFF00000000)) | np.arange(len(gram), dtype=_U)
        for shift in (1, 2, 4, 8, SPAN - 16):
            least = np.minimum(least[:-shift], least[shift:])
        window = np.repeat(lo - at - (np.cumsum(count) - count), count) + np.arange(total)
        anchor = (least[window] & _U(0xFFFFFFFF)).astype(np.int64)
        new = np.flatnonzero(np.diff(anchor, prepend=-1))
        first, last = window[new], window[np.append(new[1:], total) - 1]
        anchor = anchor[new]
        whole = (prefix[last + WIDTH] - prefix[first]) * down[first]
        whole = _mix(whole ^ _mix(((anchor - first) * 64 + (last - first) + 1).astype(_U)))
        doc = np.repeat(np.arange(len(ends)), count)[new]
        return first + at, last + at, doc, anchor + at, gram[anchor], whole

    def grams(self, n_buckets: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Distinct anchors by (bucket, hash): hash, each run's place in them, cuts between buckets."""
        gram, place = np.unique(self.gram, return_inverse=True)
        bucket = (gram % _U(n_buckets)).astype(np.int64)
        order = np.argsort(bucket, kind="stable")
        rank = np.empty_like(order)
        rank[order] = np.arange(len(order))
        return gram[order], rank[place], np.searchsorted(bucket[order], np.arange(n_buckets + 1))

    def first_equal(self, at: np.ndarray, data: np.ndarray) -> np.ndarray:
        """For each run of `at` (ascending) the first of them with the same bytes and anchor."""
        _, first, place = np.unique(self.gram[at] ^ (self.whole[at] * _U(0x9E3779B97F4A7C15)), return_index=True, return_inverse=True)
        out = at[first[place]]
        for lo in range(0, len(at), SLICE):  # equal hashes are looked at again
            i, j = at[lo : lo + SLICE], out[lo : lo + SLICE]
            other = np.flatnonzero(i != j)
            if len(other):
                x, y = i[other], j[other]
                differ = (self.last - self.first)[x] != (self.last - self.first)[y]
                differ |= (self.anchor - self.first)[x] != (self.anchor - self.first)[y]
                differ |= (self.contexts(x, data) != self.contexts(y, data)).any(axis=1)
                out[lo + other[differ]] = x[differ]
        return out

    def contexts(self, at: np.ndarray, data: np.ndarray) -> np.ndarray:
        """Bytes of runs by row, zero after each run's end."""
        index = self.first[at][:, None] + np.arange(_CONTEXT)
        return np.where(index < (self.last[at] + WIDTH)[:, None], data[np.minimum(index, len(data) - 1)], np.uint8(0))


_CONTEXT = SPAN + WIDTH - 1


def _pack(*arrays: np.ndarray) -> bytes:
    return zstandard.ZstdCompressor(level=1).compress(b"".join(np.ascontiguousarray(a).tobytes() for a in arrays))


def _unpack(blob: bytes, n: int, *kinds: str) -> list[np.ndarray]:
    raw, at, out = zstandard.ZstdDecompressor().decompress(blob), 0, []
    for kind in kinds:
        size = np.dtype(kind).itemsize * n
        out.append(np.frombuffer(raw, kind, n, at))
        at += size
    return out


def _rows(schema: dict[str, pa.DataType], rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), schema.values(), strict=True)], names=list(schema))


_BLOCK = {"block": pa.int64(), "docs": pa.int64(), "size": pa.int64(), "ids": pa.binary(), "lens": pa.binary(), "data": pa.binary()}
_BLOCK_DDL = "block long, docs long, size long, ids binary, lens binary, data binary"


def _pack_blocks(block_bytes: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = TaskContext.get().partitionId() << 32
        held: list[tuple[int, bytes]] = []
        size = 0

        def block() -> pa.RecordBatch:
            held.sort(key=lambda x: x[0])
            ids, lens = np.array([k for k, _ in held], np.int64), np.array([len(x) for _, x in held], np.int64)
            data = zstandard.ZstdCompressor(level=3).compress(b"".join(x for _, x in held))
            return _rows(_BLOCK, [(number, len(held), size, ids.tobytes(), lens.tobytes(), data)])

        for batch in batches:
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                raw = text.as_buffer().to_pybytes() if text.is_valid else b""
                if held and size + len(raw) > block_bytes:
                    yield block()
                    number, held, size = number + 1, [], 0
                held.append((key, raw))
                size += len(raw)
        if held:
            yield block()

    return run


def _opened(row: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    data = np.frombuffer(zstandard.ZstdDecompressor().decompress(row["data"]), np.uint8)
    return np.frombuffer(row["ids"], np.int64), np.frombuffer(row["lens"], np.int64), data


def _planes(x: np.ndarray, width: int) -> np.ndarray:
    """The low bytes of unsigned longs, one plane after the other."""
    return np.ascontiguousarray(x).view(np.uint8).reshape(-1, 8)[:, :width].T


def _unplaned(raw: np.ndarray, n: int, width: int) -> np.ndarray:
    out = np.zeros((n, 8), np.uint8)
    out[:, :width] = raw.reshape(width, n).T
    return out.view(_U)[:, 0]


_KEY_BYTES = 5


def _asks(n_buckets: int):
    """Entries of a block by bucket: distinct anchors, how often, and whether in several documents."""
    names = {"bucket": pa.int32(), "block": pa.int64(), "n": pa.int32(), "payload": pa.binary()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                ids, lens, data = _opened(row)
                runs = Runs(data, lens)
                gram, place, cuts = runs.grams(n_buckets)
                key = (gram // _U(n_buckets)) & _U((1 << 8 * _KEY_BYTES) - 1)
                count = np.bincount(place, minlength=len(gram))
                low, high = np.full(len(gram), len(ids)), np.full(len(gram), -1)
                np.minimum.at(low, place, runs.doc)
                np.maximum.at(high, place, runs.doc)
                seen = (np.minimum(count, 0x7FFF) * 2 + (high > low)).astype("u2")
                out = []
                for b in np.flatnonzero(np.diff(cuts)):
                    s, e = cuts[b], cuts[b + 1]
                    by = np.argsort(key[s:e], kind="stable")  # the low bits of a sorted hash are not in order
                    sent = np.diff(key[s:e][by], prepend=_U(0))
                    out.append((int(b), row["block"], int(e - s), _pack(_planes(sent, _KEY_BYTES), seen[s:e][by])))
                if out:
                    yield _rows(names, out)

    return run


def _order_of(gram: np.ndarray, cuts: np.ndarray, b: int, n_buckets: int) -> np.ndarray:
    """Places of a bucket's entries in the order they were sent."""
    s, e = cuts[b], cuts[b + 1]
    key = (gram[s:e] // _U(n_buckets)) & _U((1 << 8 * _KEY_BYTES) - 1)
    return s + np.argsort(key, kind="stable")


def _by_bucket(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, list[dict]]]:
    """Rows of each bucket; the partition is sorted by bucket."""
    held: list[dict] = []
    for batch in batches:
        for row in batch.to_pylist():
            if held and held[0]["bucket"] != row["bucket"]:
                yield held[0]["bucket"], held
                held = []
            held.append(row)
    if held:
        yield held[0]["bucket"], held


_ANSWER = {"block": pa.int64(), "bucket": pa.int32(), "n": pa.int32(), "codes": pa.binary(), "hot": pa.int64()}
_ANSWER_DDL = "block long, bucket int, n int, codes binary, hot long"
ALONE, SHARED, HOT = 0, 1, 2


def _answer(hot_runs: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Which anchors of a bucket more than one document has. Entries of one anchor come from
        different blocks and so from different documents; they are reduced row by row."""

        def opened(row: dict) -> tuple[np.ndarray, np.ndarray]:
            raw, n = np.frombuffer(zstandard.ZstdDecompressor().decompress(row["payload"]), np.uint8), row["n"]
            return np.cumsum(_unplaned(raw[: n * _KEY_BYTES], n, _KEY_BYTES), dtype=_U), raw[n * _KEY_BYTES :].view("u2").astype(np.int64)

        def reduced(keys: list[np.ndarray], seen: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
            """seen: twice the runs, plus one if in several documents; odd once two entries met."""
            key, place, met = np.unique(np.concatenate(keys), return_inverse=True, return_counts=True)
            all_ = np.concatenate(seen)
            several = np.zeros(len(key), bool)
            several[place[all_ & 1 == 1]] = True
            n = np.bincount(place, weights=all_ >> 1, minlength=len(key)).astype(np.int64)
            return key, n * 2 + (several | (met > 1))

        for bucket, rows in _by_bucket(batches):
            keys, seen, held = [], [], 0
            for r in rows:
                k, x = opened(r)
                keys.append(k)
                seen.append(x)
                held += len(k)
                if held > 2 * BUCKET_ENTRIES:
                    k, x = reduced(keys, seen)
                    keys, seen, held = [k], [x], 0
            key, total = reduced(keys, seen)
            code = np.where(total & 1 == 0, ALONE, np.where(total >> 1 > hot_runs, HOT, SHARED)).astype(np.uint8)
            hot = int((code == HOT).sum())
            for r in rows:
                k, _ = opened(r)
                yield _rows(_ANSWER, [(r["block"], bucket, r["n"], _pack(code[np.searchsorted(key, k)]), hot)])

    return run


def _result(doc: int, text: np.ndarray, marks: np.ndarray) -> tuple:
    """marks: +1 where removed bytes begin, -1 after they end (one longer than the text)."""
    gone = np.cumsum(marks[:-1]) > 0
    spans = int(np.count_nonzero(np.diff(gone.astype(np.int8), prepend=0) == 1))
    return doc, len(text), int(np.count_nonzero(gone)), spans, text[~gone].tobytes()


def _kept(raw: bytes, digest: bool) -> bytes:
    return hashlib.sha256(raw).hexdigest().encode() if digest else raw


class Asked:
    """What a block does with its answers: runs removed at once and runs to ask about."""

    def __init__(self, row: dict, n_buckets: int):
        self.ids, self.lens, self.data = _opened(row)
        self.runs = runs = Runs(self.data, self.lens)
        gram, place, cuts = runs.grams(n_buckets)
        code = np.zeros(len(gram), np.uint8)
        for a in row["answers"] or ():
            code[_order_of(gram, cuts, a["bucket"], n_buckets)] = _unpack(a["codes"], a["n"], "u1")[0]
        self.at = at = np.flatnonzero(code[place] != ALONE)
        self.first = runs.first_equal(at, self.data)
        doc = self.ids[runs.doc]
        #: Runs whose bytes an earlier document of this block has.
        self.remove = at[doc[at] > doc[self.first]]
        asked = at[self.first == at]
        hot = code[place[asked]] == HOT
        self.hot, asked = asked[hot], asked[~hot]
        bucket = (runs.gram[asked] % _U(n_buckets)).astype(np.int64)
        by = np.argsort(bucket, kind="stable")
        self.asked, self.bucket = asked[by], bucket[by]

    def sent(self, at: np.ndarray) -> bytes:
        r = self.runs
        return _pack(self.ids[r.doc[at]], r.gram[at], (r.anchor - r.first)[at].astype("u1"), (r.last - r.first)[at].astype("u1"), r.contexts(at, self.data))


def _received(row: dict) -> list[np.ndarray]:
    raw, n = np.frombuffer(zstandard.ZstdDecompressor().decompress(row["payload"]), np.uint8), row["n"]
    return [raw[: 8 * n].view(np.int64), raw[8 * n : 16 * n].view(_U), raw[16 * n : 17 * n], raw[17 * n : 18 * n], raw[18 * n :].reshape(n, _CONTEXT)]


_CONTEXTS = {"bucket": pa.int32(), "block": pa.int64(), "n": pa.int32(), "payload": pa.binary()}
_CONTEXTS_DDL = "bucket int, block long, n int, payload binary"
HOT_BUCKET = -1


def _contexts(n_buckets: int, hot: bool):
    """Bytes of the runs to refine, by bucket; or those of hot anchors."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                a = Asked(row, n_buckets)
                if hot:
                    if len(a.hot):
                        yield _rows(_CONTEXTS, [(HOT_BUCKET, row["block"], len(a.hot), a.sent(a.hot))])
                    continue
                edges = np.flatnonzero(np.diff(a.bucket, prepend=-1))  # none if the block asks nothing
                for s, e in zip(edges, np.append(edges, len(a.bucket))[1:], strict=True):
                    yield _rows(_CONTEXTS, [(int(a.bucket[s]), row["block"], int(e - s), a.sent(a.asked[s:e]))])

    return run


def _named(key: np.ndarray, live: np.ndarray) -> np.ndarray:
    """Identifiers (from 1) of the buckets that have several members; 0 for all others."""
    out = np.zeros(len(key), np.int64)
    at = np.flatnonzero(live)
    _, place, count = np.unique(key[at], return_inverse=True, return_counts=True)
    out[at] = np.where(count[place] > 1, place + 1, 0)
    return out


def least_documents(context: np.ndarray, anchor: np.ndarray, extra: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """The least document of the window at each offset of each context, by offset.

    context: bytes by row, zero after extra + 50; anchor: offset of the q-gram, at the same
    distance from the start of any two equal windows. Identifiers of the q-gram grow by one
    byte at a time to the left and to the right; a window that begins t bytes before its
    anchor is named by t bytes to the left and 26 - t to the right."""
    n, row = len(context), np.arange(len(context))
    words = np.ascontiguousarray(context[row[:, None], anchor[:, None] + np.arange(GRAM)]).view(_U)
    gram = np.ones(n, np.int64)
    for k in range(GRAM // 8):
        _, name = np.unique(words[:, k], return_inverse=True)
        gram = _named(gram << 32 | name, gram > 0)
    left, right = [gram], [gram]
    for k in range(SPAN - 1):
        at = anchor - 1 - k
        left.append(_named(left[-1] << 8 | context[row, np.maximum(at, 0)], (left[-1] > 0) & (at >= 0)))
        at = anchor + GRAM + k
        right.append(_named(right[-1] << 8 | context[row, np.minimum(at, _CONTEXT - 1)], (right[-1] > 0) & (at < extra + WIDTH)))
    out = np.repeat(doc[:, None], SPAN, axis=1)
    for t in range(SPAN):
        offset = anchor - t
        a, b = left[t], right[SPAN - 1 - t]
        at = np.flatnonzero((offset >= 0) & (offset <= extra) & (a > 0) & (b > 0))
        _, name = np.unique(a[at] << 32 | b[at], return_inverse=True)
        least = np.full(name.max(initial=-1) + 1, np.iinfo(np.int64).max)
        np.minimum.at(least, name, doc[at])
        out[at, offset[at]] = least[name]
    return out


def refine_windows(context: np.ndarray, anchor: np.ndarray, extra: np.ndarray, doc: np.ndarray, gram: np.ndarray) -> np.ndarray:
    """Bit o of answer i: the window at offset o of context i (o <= extra[i]) occurs in a
    context of a smaller document. Rows of one gram are neighbours."""
    anchor, extra = anchor.astype(np.int64), extra.astype(np.int64)
    same = (gram[1:] == gram[:-1]) & (anchor[1:] == anchor[:-1]) & (extra[1:] == extra[:-1])
    same &= (context[1:] == context[:-1]).all(axis=1)
    first = np.flatnonzero(np.append(True, ~same))  # equal neighbours are one from here on
    place = np.cumsum(np.append(True, ~same)) - 1
    least = np.minimum.reduceat(doc, first)
    hit = np.repeat((least[place] < doc)[:, None], SPAN, axis=1)
    g = gram[first]
    new = np.append(True, g[1:] != g[:-1])
    several = np.bincount(np.cumsum(new) - 1)[np.cumsum(new) - 1] > 1
    if several.any():
        at = first[several]
        found = least_documents(context[at], anchor[at], extra[at], least[several])
        number = np.cumsum(several) - 1
        member = np.flatnonzero(several[place])
        hit[member] = found[number[place[member]]] < doc[member][:, None]
    hit &= np.arange(SPAN)[None, :] <= extra[:, None]
    return (hit.astype(np.uint32) << np.arange(SPAN, dtype=np.uint32)).sum(axis=1, dtype=np.uint32)


_MIXERS = np.random.Generator(np.random.PCG64(51)).integers(0, 2**64, (_CONTEXT + 7) // 8, dtype=_U) | _U(1)


def _context_hash(context: np.ndarray) -> np.ndarray:
    wide = np.zeros((len(context), len(_MIXERS) * 8), np.uint8)
    wide[:, :_CONTEXT] = context
    return _mix((wide.view(_U) * _MIXERS).sum(axis=1, dtype=_U))


def _refine(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for bucket, rows in _by_bucket(batches):
        got = [_received(r) for r in rows]
        doc, gram, anchor, extra = (np.concatenate([g[k] for g in got]) for k in range(4))
        context = np.concatenate([g[4] for g in got])
        del got
        order = np.lexsort((_context_hash(context), gram))
        bits = np.empty(len(order), np.uint32)
        edges = np.append(np.flatnonzero(np.diff(gram[order], prepend=~gram[order[0]])), len(order))
        s = 0
        while s < len(order):
            e = int(edges[np.searchsorted(edges, min(s + SLICE, len(order)))])
            at = order[s:e]
            bits[at] = refine_windows(context[at], anchor[at], extra[at], doc[at], gram[at])
            s = e
        at, out = 0, []
        for r in rows:
            out.append((r["block"], bucket, r["n"], _pack(bits[at : at + r["n"]]), 0))
            at += r["n"]
        yield _rows(_ANSWER, out)


_WINDOWS = {"block": pa.int64(), "at": pa.int64(), "doc": pa.int64(), "bytes": pa.binary()}


def _windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The windows of hot anchors; at: 32 times the run's number in its block, plus the offset."""
    for batch in batches:
        for r in batch.to_pylist():
            doc, _, _, extra, context = _received(r)
            for lo in range(0, len(doc), 1000):
                out = [(r["block"], 32 * i + o, int(doc[i]), context[i, o : o + WIDTH].tobytes()) for i in range(lo, min(lo + 1000, len(doc))) for o in range(int(extra[i]) + 1)]
                yield _rows(_WINDOWS, out)


def _hot_answers(hot: DataFrame) -> DataFrame:
    """Offsets in runs of hot anchors that a smaller document has, gathered by block.

    Spark's minimum is partial before the shuffle; a skewed join is split by its planner."""
    windows = hot.mapInArrow(_windows, "block long, at long, doc long, bytes binary")
    least = windows.groupBy("bytes").agg(F.min("doc").alias("least"))
    hits = windows.join(least, "bytes").where("least < doc").groupBy("block").agg(F.collect_list("at").alias("at"))  # bounded by the block

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                yield _rows(_ANSWER, [(r["block"], HOT_BUCKET, len(r["at"]), _pack(np.array(r["at"], np.int64)), 0)])

    return hits.mapInArrow(run, _ANSWER_DDL)


def _finish(n_buckets: int, digest: bool):
    names = {"doc": pa.int64(), "n_bytes": pa.int64(), "n_removed": pa.int64(), "n_spans": pa.int64(), "kept": pa.binary()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                a = Asked(row, n_buckets)
                runs, lens = a.runs, a.lens
                bits = np.zeros(len(runs.first), np.uint32)
                for got in row["refined"] or ():
                    if got["bucket"] == HOT_BUCKET:
                        at = _unpack(got["codes"], got["n"], "i8")[0]
                        np.bitwise_or.at(bits, a.hot[at // 32], np.uint32(1) << (at % 32).astype(np.uint32))
                        continue
                    s, e = np.searchsorted(a.bucket, [got["bucket"], got["bucket"] + 1])
                    bits[a.asked[s:e]] = _unpack(got["codes"], got["n"], "u4")[0]
                bits[a.at] = bits[a.first]  # repeated rows of one id share the answer
                bits[a.remove] = (np.uint32(2) << (runs.last - runs.first)[a.remove].astype(np.uint32)) - np.uint32(1)
                marks = np.zeros(len(a.data) + len(lens), np.int32)  # a spare place after each document
                for o in range(SPAN):
                    hit = np.flatnonzero(bits >> np.uint32(o) & np.uint32(1))
                    place = runs.first[hit] + runs.doc[hit] + o  # document i begins i places later there
                    np.add.at(marks, place, 1)
                    np.add.at(marks, place + WIDTH, -1)
                ends = np.cumsum(lens)
                out = []
                for i in range(len(lens)):
                    s, e = ends[i] - lens[i], ends[i]
                    *numbers, raw = _result(int(a.ids[i]), a.data[s:e], marks[s + i : e + i + 1])
                    out.append((*numbers, _kept(raw, digest)))
                for lo in range(0, len(out), 1000):
                    yield _rows(names, out[lo : lo + 1000])

    return run


def dedup_substrings(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", digest: bool = False, block_bytes: int = BLOCK_BYTES, hot_runs: int = HOT_RUNS) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept of every row.

    kept: the bytes that stay (digest: their SHA-256 in hex, as bytes). Null text is
    empty; a null id counts as smaller than all. Rows with equal ids do not remove each
    other's bytes; repeated rows repeat. Texts under 50 bytes stay as they are; a text longer
    than block_bytes is a block of its own. Other columns are not read."""
    spark = docs.sparkSession
    key = F.coalesce(F.col(id_col).cast("long"), F.lit(NULL_KEY))
    blocks = Staged(docs.select(key.alias("key"), F.col(text_col).cast("string").alias("text")).mapInArrow(_pack_blocks(block_bytes), _BLOCK_DDL), "substring-blocks", "none")
    size = blocks.df.agg(F.sum("size")).first()[0] or 0
    n = max(partitions(spark), int(size * 2 / (SPAN + 1) / BUCKET_ENTRIES) + 1)
    asks = blocks.df.mapInArrow(_asks(n), "bucket int, block long, n int, payload binary")
    answers = Staged(asks.repartition(n, "bucket").sortWithinPartitions("bucket").mapInArrow(_answer(hot_runs), _ANSWER_DDL), "substring-answers")
    any_hot = answers.df.agg(F.max("hot")).first()[0]

    def gathered(answers: DataFrame, name: str) -> DataFrame:
        return answers.groupBy("block").agg(F.collect_list(F.struct("bucket", "n", "codes")).alias(name))  # one row per bucket at most

    told = blocks.df.join(gathered(answers.df, "answers"), "block", "left")
    contexts = told.mapInArrow(_contexts(n, False), _CONTEXTS_DDL)
    refined = contexts.repartition(n, "bucket").sortWithinPartitions("bucket").mapInArrow(_refine, _ANSWER_DDL)
    if any_hot:
        refined = refined.unionAll(_hot_answers(told.mapInArrow(_contexts(n, True), _CONTEXTS_DDL)))
    refined = Staged(refined, "substring-refined")
    last = told.join(gathered(refined.df, "refined"), "block", "left")
    got = last.mapInArrow(_finish(n, digest), "doc long, n_bytes long, n_removed long, n_spans long, kept binary")
    return got.select(F.when(F.col("doc") != NULL_KEY, F.col("doc")).alias("doc_id"), "n_bytes", "n_removed", "n_spans", "kept")
