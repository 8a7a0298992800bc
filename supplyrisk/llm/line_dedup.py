"""Line dedup on content-defined chunks of lines.

A rolling hash over the hashes of the last two lines marks a line where, mixed by a prime
modulus, it is divisible by CHUNK_LINES. A mark ends a chunk, but not of fewer than MIN_LINES
lines (of marks in a row every second one counts, the text's start being one), and between
two such ends a chunk ends after every MAX_LINES lines if at least MIN_LINES follow. All of
it depends on the lines around alone, so an inserted or lost line moves only the boundaries
next to it, and a run of equal lines falls into equal chunks. Chunks of at least MIN_LINES
lines that occur more than once over all documents keep their first occurrence (smallest
id, then place); the others go, after their bytes are compared.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from supplyrisk.llm.common import order_key, stage

CHUNK_LINES = 4
MIN_LINES = 2
MAX_LINES = 8
#: Rolling: h(previous line) * ROLL + h(line), with hashes of 28 bits; then modulo MIXER.
ROLL, MIXER = 31, 1_000_003
#: A chunk that holds more than one in so many of the rows is joined without a shuffle.
HOT_SHARE = 1000


def line_hash(line: bytes) -> int:
    return int(hashlib.md5(line, usedforsecurity=False).hexdigest()[:7], 16)


def chunk_ends(lines: list[bytes]) -> np.ndarray:
    """Numbers (from 0) of the lines that end a chunk, ascending; the last line always does."""
    known: dict[bytes, int] = {}
    h = np.fromiter((known[x] if x in known else known.setdefault(x, line_hash(x)) for x in lines), np.int64, len(lines))
    rolled = h.copy()
    rolled[1:] += h[:-1] * ROLL
    marks = np.append(-1, np.flatnonzero(rolled % MIXER % CHUNK_LINES == 0))
    at = np.arange(len(marks))
    begins = np.append(True, np.diff(marks) > 1)  # of marks in a row
    ends = marks[(at - np.maximum.accumulate(np.where(begins, at, 0))) % 2 == 0]
    past = np.append(ends[1:], len(lines) - 1)
    more = np.maximum((past - MIN_LINES - ends) // MAX_LINES, 0)
    out = np.repeat(ends, more + 1) + MAX_LINES * (np.arange(len(ends) + more.sum()) - np.repeat(np.cumsum(more + 1) - more - 1, more + 1))
    return np.union1d(out[out >= 0], [len(lines) - 1])


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), order_key(id_col).alias("k"), F.xxhash64(text).alias("h"), text.alias("text"))


def _chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """k, h, first, past (line numbers) and c (hash of the bytes) of each chunk that may repeat."""
    names = ["k", "h", "first", "past", "c"]

    def sent(out: list[tuple]) -> pa.RecordBatch:
        kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64())
        return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out, strict=True), kinds, strict=True)], names=names)

    out: list[tuple] = []
    for batch in batches:
        for k, h, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
            lines = text.as_buffer().to_pybytes().split(b"\n")
            first = 0
            for past in (chunk_ends(lines) + 1).tolist():
                if past - first >= MIN_LINES:
                    body = b"\n".join(lines[first:past])
                    if body.strip(b" "):
                        out.append((k, h, first, past, (xxhash.xxh64_intdigest(body, 42) ^ (1 << 63)) - (1 << 63)))
                first = past
            if len(out) >= 50_000:
                yield sent(out)
                out = []
    if out:
        yield sent(out)


def _repeats(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """k, h, repeats: for each row (order key, text hash) its chunks whose hash occurs more
    than once, and whether one is the first. Rows of equal id and text are one document.

    Chunks with over 1 / HOT_SHARE of all rows, fewer than HOT_SHARE of them, are sent to
    every executor instead of gathering their rows in one task."""
    chunks = _rows(docs, id_col, text_col).select("k", "h", "text").mapInArrow(_chunks, "k long, h long, first int, past int, c long")
    narrow = stage(chunks.distinct(), "line-chunks")
    place = F.struct("k", "h", "first")
    shared = stage(narrow.groupBy("c").agg(F.count("*").alias("n"), F.min(place).alias("keep")).where("n > 1"), "line-shared")
    limit = narrow.count() // HOT_SHARE
    hot, others = F.broadcast(shared.where(F.col("n") > limit)), shared.where(F.col("n") <= limit)
    found = narrow.join(hot, "c").unionByName(narrow.join(hot, "c", "left_anti").join(others.hint("merge"), "c"))
    found = found.withColumn("stays", place == F.col("keep"))
    return found.groupBy("k", "h").agg(F.array_sort(F.collect_set(F.struct("first", "past", "c", "stays"))).alias("repeats"))


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_lines, removed_chunks, removed_lines, text of every row.

    Null text is empty (one empty line); a null id comes before all others. Repeated rows
    repeat: rows of equal id and text are treated alike. Texts of any number of lines are
    taken whole. Other columns are not read. Empty input: no rows.

    Texts meet their repeated chunks once, by row (so a chunk in a third of all documents
    is no hot key there), and are staged. Bytes are compared by grouping the repeated
    chunks by hash and text; if a hash turns out to have several texts, its chunks are
    decided again by text."""
    repeats = _repeats(docs, id_col, text_col)
    rows = _rows(docs, id_col, text_col)
    joined = rows.join(repeats.hint("merge"), ["k", "h"], "left")
    met = stage(joined.select("doc_id", "k", "h", "text", "repeats"), "line-met").withColumn("lines", F.split("text", "\n"))
    chunk = F.array_join(F.slice("lines", F.col("first") + 1, F.col("past") - F.col("first")), "\n")
    texts = met.where("repeats is not null").select("k", "h", "lines", F.inline("repeats")).select("c", chunk.alias("chunk"), F.struct("k", "h", "first").alias("place"))
    kinds = texts.groupBy("c", "chunk").agg(F.min("place").alias("keep"))
    odd = stage(kinds.groupBy("c").agg(F.count("*").alias("n")).where("n > 1").select("c"), "line-odd")
    spans = F.filter(F.coalesce("repeats", F.array().cast("array<struct<first:int,past:int,c:bigint,stays:boolean>>")), lambda x: ~x["stays"])
    if odd.limit(1).count():  # 64-bit hashes of different texts met
        again = texts.join(odd, "c").join(kinds.join(odd, "c"), ["c", "chunk"]).where("place = keep")
        first = again.select("place.*").groupBy("k", "h").agg(F.collect_set("first").alias("firsts"))
        met = met.join(first, ["k", "h"], "left")
        spans = F.filter(spans, lambda x: ~F.coalesce(F.array_contains(F.col("firsts"), x["first"]), F.lit(False)))
    # What stays: before, between and after the removed stretches.
    gone = met.withColumn("gone", spans)
    starts = F.concat(F.array(F.lit(0)), F.transform("gone", lambda s: s["past"]))
    ends = F.concat(F.transform("gone", lambda s: s["first"]), F.array(F.size("lines")))
    kept = F.flatten(F.zip_with(starts, ends, lambda s, e: F.slice(F.col("lines"), s + 1, e - s)))
    removed = F.aggregate("gone", F.lit(0), lambda a, s: a + s["past"] - s["first"])
    return gone.select("doc_id", F.size("lines").alias("n_lines"), F.size("gone").alias("removed_chunks"), removed.alias("removed_lines"), F.array_join(kept, "\n").alias("text"))
