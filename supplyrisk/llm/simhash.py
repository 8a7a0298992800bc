"""SimHash near duplicates with pigeonring pruning.

A fingerprint bit is set if it is set in over half of the shingle hashes; documents link
at `MAX_BITS` or fewer differing bits and a component is what links reach.

The 64 bits form a ring of five segments. If two fingerprints differ in at most four bits,
some segment starts a chain in which the first l segments together differ in at most
4l/5 bits, for every l (the pigeonring principle): 0 in the first, 1 in two, 2 in three,
3 in four. So one half of the second segment is equal too, and fingerprints are dealt by
(segment number, segment, half of the next one); in a partition the other half is looked up
with none or one bit changed; longer chains are checked in turn, and only what is left
gets the full Hamming test.

`near_duplicates` links at MAX_BITS of one 64-bit word. `near_groups` links texts whose sets
of five-word shingles (64-bit hashes) have a Jaccard similarity of at least LEAST_JACCARD.
At 0.8 such texts differ in 39 of 256 SimHash bits on average, too many to deal fingerprints
by segments; they are dealt by BANDS bands of ROWS min-wise hashes, which misses a pair at
0.8 with probability (1 - 0.8^4)^16 = 0.0002. Of what meets in a band, pigeonring chains over
the 256-bit ring (budget WIDE_TOTAL) prune, then the full Hamming test, and each pair left is
confirmed on the two sets themselves.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from supplyrisk.llm.common import partitions, shared_dir, stage

SHINGLE_WORDS = 4
MAX_BITS = 4
SEED = 42
#: Of near groups: sets with at least this Jaccard similarity link; bands and minima in each.
LEAST_JACCARD, BANDS, ROWS = (4, 5), 16, 4
NEAR_SHINGLE_WORDS = 5
#: Wide SimHash: words of 64 bits, segments of its ring, and bits that may differ. At Jaccard 0.8
#: (cosine 0.89) 39 differ with a deviation of 6; of unrelated texts 128 with one of 8.
WIDE_WORDS, WIDE_SEGMENTS, WIDE_TOTAL = 4, 16, 80
#: Shingles of one bucket that a task holds at once; larger buckets go by pairs of blocks.
BLOCK_SHINGLES = 1_000_000
#: Bands are worked on in these steps: what the first ones joined is not sent again.
BAND_STEPS = ((0, 3), (3, BANDS))
#: Pairs compared at once in a task.
PAIR_BLOCK = 2_000_000
#: Rows (ten for each distinct fingerprint) that one task should get.
ROWS_PER_TASK = 200_000
#: Ids (8 bytes) up to which a list of documents to drop is sent to every executor.
BROADCAST_IDS = 1_000_000

_LOWER = bytes.maketrans(bytes(range(65, 91)), bytes(range(97, 123)))


def _shingle_hashes(text: str | None, words: int) -> np.ndarray:
    """Hash of each shingle, repeats included; of the whole sequence if it is shorter."""
    parts = (text or "").encode("utf-8", "surrogatepass").translate(_LOWER).split()
    if not parts:
        return np.empty(0, np.uint64)
    norm, n = b" ".join(parts), len(parts)
    digest = xxhash.xxh64_intdigest
    if n <= words:
        return np.array([digest(norm, SEED)], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, parts), np.int64, n) + 1)
    starts = np.concatenate(([0], ends[: n - words])).tolist()
    return np.array([digest(norm[s:e], SEED) for s, e in zip(starts, (ends[words - 1 :] - 1).tolist(), strict=True)], np.uint64)


def _majority(hashes: np.ndarray) -> int:
    """Bits set in over half of the hashes."""
    counts = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 65_536):
        part = hashes[at : at + 65_536].astype(">u8").view(np.uint8).reshape(-1, 8)
        counts += np.unpackbits(part, axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(counts * 2 > len(hashes)).tobytes(), "big")


def fingerprint(text: str | None, words: int = SHINGLE_WORDS) -> int:
    """Unsigned 64-bit SimHash of one text; zero if it has no word."""
    return _majority(_shingle_hashes(text, words))


def wide_fingerprint(shingles: np.ndarray) -> np.ndarray:
    """WIDE_WORDS SimHash words of a set of shingle hashes, remixed for each word."""
    out = np.empty(WIDE_WORDS, np.uint64)
    for k in range(WIDE_WORDS):
        x = (shingles ^ (shingles >> np.uint64(32))) * np.uint64(0x9E3779B97F4A7C15 + 2 * 0x632BE59BD9B4E019 * k & (1 << 64) - 1)
        x = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
        out[k] = _majority(x ^ (x >> np.uint64(32)))
    return out


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and fp (the 64 bits as a signed long) of every row; null text is empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = np.array([fingerprint(x.as_py()) for x in batch.column(1)], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fps)], names=["doc_id", "fp"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "doc_id long, fp long")


def _popcount(x: np.ndarray) -> np.ndarray:
    return np.bitwise_count(x)


def _labels(n: int, a: np.ndarray, b: np.ndarray, label: np.ndarray | None = None) -> np.ndarray:
    """Smallest index reachable, by hooking roots to smaller ones and halving paths."""
    label = np.arange(n) if label is None else label
    while True:
        x, y = label[a], label[b]
        open_ = x != y
        if not open_.any():
            return label
        a, b, x, y = a[open_], b[open_], x[open_], y[open_]
        np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
        while True:
            up = label[label]
            if (up == label).all():
                break
            label = up


def ring(bits: int) -> list[tuple[int, int]]:
    """Shift and width of each segment: bits + 1 of them, as equal as can be."""
    n = bits + 1
    cuts = [64 * i // n for i in range(n + 1)]
    return [(a, b - a) for a, b in zip(cuts, cuts[1:], strict=False)]


def _segment(fp: np.ndarray, place: tuple[int, int]) -> np.ndarray:
    return (fp >> np.uint64(place[0])) & np.uint64((1 << place[1]) - 1)


def _halves(place: tuple[int, int]) -> list[tuple[int, int]]:
    """The two halves of a segment, low one first."""
    shift, width = place
    return [(shift, width // 2), (shift + width // 2, width - width // 2)]


def ring_links(fp: np.ndarray, table: np.ndarray, half: np.ndarray, bits: int = MAX_BITS) -> tuple[np.ndarray, np.ndarray]:
    """Spanning links (index pairs) among fingerprints dealt by the segment `table` names and
    one half of the next.

    Every pair within `bits` whose chain starts at that segment and that has this half in
    common ends up connected."""
    places = ring(bits)
    out_a, out_b = [], []
    for t, h in ((t, h) for t in range(len(places)) for h in (0, 1)):
        rows = np.flatnonzero((table == t) & (half == h))
        if len(rows) < 2:
            continue
        f = fp[rows]
        n, at_next = len(f), (t + 1) % len(places)
        same, other = _halves(places[at_next])[h], _halves(places[at_next])[1 - h]
        key = (_segment(f, places[t]) << np.uint64(32)) | (_segment(f, same) << np.uint64(16)) | _segment(f, other)
        order = np.argsort(key, kind="stable")
        f, key, rows = f[order], key[order], rows[order]

        def linked(a: np.ndarray, b: np.ndarray, f: np.ndarray = f) -> np.ndarray:
            return _popcount(f[a] ^ f[b]) <= bits

        # Linear start: neighbours in the order that leaves out one nibble.
        label = np.arange(n)
        for nibble in range(16):
            rest = f & ~np.uint64(0xF << (4 * nibble))
            o = np.argsort(rest, kind="stable")
            met = np.flatnonzero(rest[o[1:]] == rest[o[:-1]])
            a, b = o[met], o[met + 1]
            keep = linked(a, b)
            label = _labels(n, a[keep], b[keep], label)
        # Pairs with both halves equal meet in both tables; the first one takes them.
        for bit in (*((-1,) if h == 0 else ()), *range(other[1])):
            want = key if bit < 0 else key ^ np.uint64(1 << bit)
            lo = np.maximum(np.searchsorted(key, want, "left"), np.arange(n) + 1)  # each pair once
            size = np.maximum(np.searchsorted(key, want, "right") - lo, 0)
            ends = np.cumsum(size)
            at = 0
            while at < n:
                done = ends[at - 1] if at else 0
                upto = max(at + 1, int(np.searchsorted(ends, done + PAIR_BLOCK, "right")))
                part = size[at:upto]
                if part.any():
                    a = np.repeat(np.arange(at, upto), part)
                    b = np.arange(len(a)) - np.repeat(np.cumsum(part) - part, part) + np.repeat(lo[at:upto], part)
                    keep = label[a] != label[b]
                    a, b = a[keep], b[keep]
                    chain = _popcount(_segment(f[a] ^ f[b], places[at_next])).astype(np.int64)
                    for length in range(3, len(places)):
                        x = f[a] ^ f[b]
                        chain = chain + _popcount(_segment(x, places[(t + length - 1) % len(places)]))
                        keep = chain <= length - 1
                        a, b, chain = a[keep], b[keep], chain[keep]
                    keep = linked(a, b)
                    label = _labels(n, a[keep], b[keep], label)
                at = upto
        joined = np.flatnonzero(label != np.arange(n))
        out_a.append(rows[joined])
        out_b.append(rows[label[joined]])
    if not out_a:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    return np.concatenate(out_a), np.concatenate(out_b)


def links(reps: DataFrame, bits: int = MAX_BITS) -> DataFrame:
    """Spanning links (a > b, ids) among representatives `rep` with distinct `fp` that are
    within `bits`."""
    spark = reps.sparkSession
    places = ring(bits)

    def part(place: tuple[int, int]) -> F.Column:
        return F.shiftrightunsigned("fp", place[0]).bitwiseAND(F.lit((1 << place[1]) - 1))

    dealt = [F.struct(F.lit(t).alias("ring"), F.lit(h).alias("half"), F.shiftleft(part(places[t]), 32).bitwiseOR(part(same)).alias("key")) for t in range(len(places)) for h, same in enumerate(_halves(places[(t + 1) % len(places)]))]
    n = max(partitions(spark), len(dealt) * reps.count() // ROWS_PER_TASK + 1)
    rows = reps.select("rep", "fp", F.inline(F.array(*dealt))).repartition(n, "ring", "half", "key").select("rep", "fp", "ring", "half")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [[b.column(i).to_numpy() for i in range(4)] for b in batches if b.num_rows]
        if not parts:
            return
        rep, fp, at, half = (np.concatenate(x) for x in zip(*parts, strict=True))
        a, b = ring_links(fp.view(np.uint64), at, half, bits)
        x, y = rep[a], rep[b]
        yield pa.RecordBatch.from_arrays([pa.array(np.maximum(x, y)), pa.array(np.minimum(x, y))], names=["a", "b"])

    return rows.mapInArrow(run, "a long, b long").distinct()


def components(edges: DataFrame) -> DataFrame:
    """node, root (smallest id reachable) of every node of the edges (a > b).

    Alternating star contraction; each round is cut with checkpoint()."""
    shared_dir(edges.sparkSession)
    edges = edges.checkpoint()
    while True:
        both = edges.select(F.col("a").alias("u"), F.col("b").alias("v")).union(edges.select("b", "a"))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        down = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(down, "a")
        new = small.select(F.col("b").alias("a"), F.col("m").alias("b")).union(small.select("a", F.col("m").alias("b"))).where("a <> b").distinct().checkpoint()
        # A fixed point is a set of stars: no node is both a leaf and a root, one root each.
        roots = new.select(F.col("b").alias("a")).distinct()
        crossing = new.join(roots, "a", "left_semi").limit(1).count()
        several = new.groupBy("a").count().where("count > 1").limit(1).count()
        edges = new
        if not crossing and not several:
            return edges.select(F.col("a").alias("node"), F.col("b").alias("root"))


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, fp, component_id of every row.

    Null text is empty (fingerprint zero); a null id takes part in nothing and is its own
    (null) component unless a document with an id has its fingerprint. Repeated rows
    repeat. Pairs are never listed: copies meet in one representative per fingerprint."""
    prints = stage(fingerprints(docs, id_col, text_col), "simhash")
    reps = prints.groupBy("fp").agg(F.min("doc_id").alias("rep")).where("rep is not null")
    reps = stage(reps, "simhash-reps")
    roots = components(links(reps))
    named = reps.join(roots, reps["rep"] == roots["node"], "left").select("fp", F.coalesce("root", "rep").alias("component_id"))
    return prints.join(named, "fp", "left").select("doc_id", "fp", "component_id")


def shingle_set(text: str | None) -> np.ndarray:
    """Sorted distinct hashes of the five-word shingles of one text."""
    return np.unique(_shingle_hashes(text, NEAR_SHINGLE_WORDS))


def band_keys(shingles: np.ndarray) -> list[int]:
    """A signed key of each band; sets of no shingle have none."""
    if not len(shingles):
        return []
    least = np.full(BANDS * ROWS, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(shingles), 8_192):
        x = shingles[None, at : at + 8_192] * _FACTORS + _SHIFTS
        x = (x ^ (x >> np.uint64(32))) * np.uint64(0xBF58476D1CE4E5B9)
        np.minimum(least, (x ^ (x >> np.uint64(29))).min(axis=1), out=least)
    return [xxhash.xxh64_intdigest(least[k * ROWS : (k + 1) * ROWS].tobytes(), k) - (1 << 63) for k in range(BANDS)]


_RANDOM = np.random.default_rng(SEED)
_FACTORS = _RANDOM.integers(0, 1 << 64, (BANDS * ROWS, 1), np.uint64) | np.uint64(1)
_SHIFTS = _RANDOM.integers(0, 1 << 64, (BANDS * ROWS, 1), np.uint64)


def chains(apart: np.ndarray) -> np.ndarray:
    """Rows (differing bits by segment) with a chain: from some segment on, the first l segments
    together differ in at most l / WIDE_SEGMENTS of WIDE_TOTAL bits, for every l."""
    turned = np.concatenate([apart, apart], axis=1).astype(np.int64)
    live = np.ones(apart.shape, bool)
    total = np.zeros(apart.shape, np.int64)
    for length in range(1, WIDE_SEGMENTS + 1):
        total += turned[:, length - 1 : length - 1 + WIDE_SEGMENTS]
        live &= total * WIDE_SEGMENTS <= length * WIDE_TOTAL
    return live.any(axis=1)


def similar_links(sets: list[np.ndarray], wide: np.ndarray, label: np.ndarray | None = None, block: np.ndarray | None = None) -> tuple[list[int], list[int]]:
    """Spanning links (index pairs) among non-empty sets: all pairs of at least LEAST_JACCARD
    end up connected. Only pairs that are joined already are skipped. wide: the SimHash words
    of each set (rows). label: what is joined before. block: only pairs of two blocks."""
    over, under = LEAST_JACCARD
    n = len(sets)
    sizes = np.array([len(s) for s in sets], np.int64)
    values, ids = np.unique(np.concatenate(sets), return_inverse=True)
    starts = np.concatenate(([0], np.cumsum(sizes)))
    label = np.arange(n) if label is None else np.unique(label, return_inverse=True)[1]
    mark = np.zeros(len(values), bool)
    segments = np.ascontiguousarray(wide).view(np.uint16).reshape(n, WIDE_SEGMENTS)
    out_a, out_b = [], []
    for i in range(n - 1):
        j = np.arange(i + 1, n)
        keep = (label[j] != label[i]) & (np.minimum(sizes[j], sizes[i]) * under >= np.maximum(sizes[j], sizes[i]) * over)
        if block is not None:
            keep &= block[j] != block[i]
        j = j[keep]
        if len(j):
            apart = np.bitwise_count(segments[j] ^ segments[i])
            # The first segment of a chain alone prunes most; then whole chains, then the Hamming test.
            near = (apart * WIDE_SEGMENTS <= WIDE_TOTAL).any(axis=1)
            j, apart = j[near], apart[near]
            near = chains(apart)
            j, apart = j[near], apart[near]
            j = j[apart.sum(axis=1, dtype=np.int64) <= WIDE_TOTAL]
        if not len(j):
            continue
        own = ids[starts[i] : starts[i + 1]]
        mark[own] = True
        size = sizes[j]
        ends = np.cumsum(size)
        members = ids[np.repeat(starts[j] - (ends - size), size) + np.arange(ends[-1])]
        shared = np.add.reduceat(mark[members].astype(np.int64), ends - size)
        mark[own] = False
        j = j[shared * under >= over * (sizes[j] + sizes[i] - shared)]
        if len(j):
            roots, first = np.unique(label[j], return_index=True)
            out_a += [i] * len(first)
            out_b += j[first].tolist()
            label[np.isin(label, roots)] = label[i]
    return out_a, out_b


def _similar(sets: DataFrame, banded: DataFrame, block_shingles: int) -> DataFrame:
    """Confirmed spanning links (a > b, ids). sets: rep, d0, d1, wide, shingles; banded: rep,
    d0, d1, n (shingles), key, label (of what is joined).

    A key whose sets together pass block_shingles is dealt as pairs of blocks of its rows."""
    keys = banded.groupBy("key").agg(F.ceil(F.sum("n") / block_shingles).cast("int").alias("blocks"), (F.min("label") < F.max("label")).alias("several")).where("several").drop("several")
    met = banded.join(keys, "key").withColumn("own", F.pmod(F.xxhash64("rep", "d0", "d1"), F.col("blocks")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    met = met.withColumn("other", other).select("key", F.least("own", "other").alias("x"), F.greatest("own", "other").alias("y"), "own", "rep", "d0", "d1", "label")
    met = met.join(sets, ["rep", "d0", "d1"]).select("key", "x", "y", "own", "rep", "label", "wide", "shingles")

    def links_of(held: list[tuple], pair: tuple) -> Iterator[pa.RecordBatch]:
        if len(held) > 1:
            block, rep, label = (np.array(x, np.int64) for x in list(zip(*held, strict=True))[:3])
            wide = np.array([h[3] for h in held], np.int64).view(np.uint64)
            a, b = similar_links([np.frombuffer(h[4], np.uint64) for h in held], wide, label, None if pair[1] == pair[2] else block)
            p, q = rep[a], rep[b]
            apart = p != q
            yield pa.RecordBatch.from_arrays([pa.array(np.maximum(p, q)[apart]), pa.array(np.minimum(p, q)[apart])], names=["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []
        for batch in batches:  # in the order of keys: one pair of blocks is held at a time
            for key, x, y, *row in zip(*(batch.column(i).to_pylist() for i in range(8)), strict=True):
                if (key, x, y) != now:
                    yield from links_of(held, now)
                    now, held = (key, x, y), []
                held.append(tuple(row))
        yield from links_of(held, now)

    dealt = met.repartition(partitions(sets.sparkSession), "key", "x", "y").sortWithinPartitions("key", "x", "y")
    return dealt.mapInArrow(run, "a long, b long").distinct()


def _digest(shingles: np.ndarray) -> tuple[int, int]:
    x = xxhash.xxh128_intdigest(shingles.tobytes(), SEED)
    return (x >> 64) - (1 << 63), (x & (1 << 64) - 1) - (1 << 63)


def _sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        sets = [shingle_set(x.as_py()) for x in batch.column(1)]
        d = np.array([_digest(s) for s in sets], np.int64).reshape(-1, 2)
        sizes = np.array([len(s) for s in sets], np.int64)
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(d[:, 0].copy()), pa.array(d[:, 1].copy()), pa.array(sizes), pa.array([band_keys(s) for s in sets], pa.list_(pa.int64()))], names=["doc_id", "d0", "d1", "n", "bands"])


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    kinds = pa.schema([("rep", pa.int64()), ("d0", pa.int64()), ("d1", pa.int64()), ("wide", pa.list_(pa.int64())), ("shingles", pa.binary())])
    for batch in batches:
        out = []
        for rep, text in zip(*(batch.column(i).to_pylist() for i in range(2)), strict=True):
            s = shingle_set(text)
            out.append((rep, *_digest(s), wide_fingerprint(s).view(np.int64), s.tobytes()))
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], kinds.field(i).type) for i in range(5)], schema=kinds)


def _prints(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """doc_id, d0, d1 (digest of the shingle set), n (its size) and bands of every row; staged."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return stage(rows.mapInArrow(_sketch, "doc_id long, d0 long, d1 long, n long, bands array<long>"), "near")


def near_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", prints: DataFrame | None = None, block_shingles: int = BLOCK_SHINGLES) -> DataFrame:
    """doc_id, group_id (smallest id reachable) by confirmed similarity.

    Texts of one shingle set meet in one representative. A null text is empty, and texts
    without a word are one group; a null id takes part in nothing and has a null group
    unless a document with an id has its set. Rows of one id with different texts join their groups. Repeated rows repeat.
    Sets are made again, and moved, only for representatives that share a band with another
    one; of later bands only keys that still hold several groups."""
    prints = _prints(docs, id_col, text_col) if prints is None else prints
    reps = stage(prints.groupBy("d0", "d1").agg(F.min("doc_id").alias("rep"), F.first("n").alias("n"), F.first("bands").alias("bands")).where("rep is not null"), "near-reps")
    banded = reps.select("rep", "d0", "d1", "n", F.posexplode("bands").alias("band", "key"))
    shared = banded.groupBy("key").agg(F.count("*").alias("members")).where("members > 1").select("key")
    banded = stage(banded.join(shared, "key", "left_semi"), "near-banded")
    wanted = banded.select("rep").distinct()
    if wanted.count() <= BROADCAST_IDS:
        wanted = F.broadcast(wanted)
    rows = docs.select(F.col(id_col).cast("long").alias("rep"), F.col(text_col).cast("string").alias("text"))
    made = rows.join(wanted, "rep", "left_semi").mapInArrow(_sets, "rep long, d0 long, d1 long, wide array<long>, shingles binary")
    sets = stage(made.groupBy("rep", "d0", "d1").agg(F.first("wide").alias("wide"), F.first("shingles").alias("shingles")), "near-sets")
    edges, roots = None, None
    for low, high in BAND_STEPS:
        part = banded.where((F.col("band") >= low) & (F.col("band") < high))
        if roots is None:
            part = part.withColumn("label", F.col("rep"))
        else:
            part = part.join(roots, part["rep"] == roots["node"], "left").withColumn("label", F.coalesce("root", "rep")).drop("node", "root")
        found = stage(_similar(sets, part, block_shingles), "near-links")
        edges = found if edges is None else edges.unionAll(found)
        roots = components(edges)
    named = reps.join(roots, reps["rep"] == roots["node"], "left").select("d0", "d1", F.coalesce("root", "rep").alias("group_id"))
    return prints.join(named, ["d0", "d1"], "left").select("doc_id", "group_id")


def keep_representatives(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The row with the smallest id of each near group, with its own columns.

    Of rows that share an id and a text one stays; rows with a null id all stay. Texts are not shuffled unless the list of documents that go passes BROADCAST_IDS, or ids repeat."""
    prints = _prints(docs, id_col, text_col)
    lost = stage(near_groups(docs, id_col, text_col, prints).where("group_id < doc_id").select(F.col("doc_id").alias("__lost")).distinct(), "near-lost")
    if lost.count() <= BROADCAST_IDS:
        lost = F.broadcast(lost)
    left = docs.join(lost, docs[id_col].cast("long") == lost["__lost"], "left_anti")
    again = stage(prints.where("doc_id is not null").groupBy("doc_id", "d0", "d1").agg(F.count("*").alias("n")).where("n > 1").select(F.col("doc_id").alias("__again")).distinct(), "near-again")
    if not again.limit(1).count():
        return left
    repeated = docs[id_col].cast("long") == again["__again"]
    few = left.join(again, repeated, "left_semi").withColumn("__h", F.xxhash64(F.coalesce(F.col(text_col).cast("string"), F.lit(""))))
    one = few.withColumn("__n", F.row_number().over(Window.partitionBy(id_col, "__h").orderBy(id_col))).where("__n = 1")
    return left.join(again, repeated, "left_anti").unionByName(one.select(*docs.columns))
