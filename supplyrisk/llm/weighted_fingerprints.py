"""Document fingerprints by consistent weighted sampling.

Terms are adjacent word pairs in lower case, weighted by how often they occur (and, for
texts of under SHORT_WORDS words, also character triples). For each of SAMPLES samples a
term has gamma variates r and c and a uniform b that depend on the term and the sample
alone; its weight w is quantised to t = floor(ln w / r + b), and the sample is the term
with the least c / (exp(r (t - b)) e^r), with its t. Two texts agree in a sample with a
probability equal to the generalised Jaccard similarity of their weights.

Terms are 64-bit hashes, and the variates of a (term, sample) are made from a hash of the
two, so they need no table of terms and no two terms of a text share them. Terms are worked
on in slices, so a text of any length takes bounded memory. A sample is kept in 16 bits, so
unlike samples agree by chance once in 65,536.
"""

from __future__ import annotations

import functools
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from supplyrisk.llm.common import NULL_KEY, bucket_count, bucket_of, key_bounds, order_key, partitions

SAMPLES = 64
SHORT_WORDS = 8
#: Terms whose variates are made at once.
SLICE = 2_048
SEED = 20_011
_WORD_CACHE = 300_000
_PAIR = np.uint64(0x9E3779B97F4A7C15)
_MIX = np.uint64(0xBF58476D1CE4E5B9)


class _Words(dict):
    """Word to 64-bit hash, kept while it stays small."""

    def __missing__(self, word: str) -> int:
        if len(self) > _WORD_CACHE:
            self.clear()
        self[word] = h = xxhash.xxh64_intdigest(word, SEED)
        return h


_words = _Words()


@functools.cache
def _salts(samples: int) -> np.ndarray:
    return np.random.Generator(np.random.PCG64(SEED)).integers(0, 2**64, samples, dtype=np.uint64)


@functools.cache
def _gamma_quantiles() -> np.ndarray:
    """Gamma(2, 1) at the middles of 65,536 equal parts, by bisection."""
    p = (np.arange(1 << 16) + 0.5) / (1 << 16)
    low, high = np.zeros(1 << 16), np.full(1 << 16, 40.0)
    for _ in range(60):
        at = (low + high) / 2
        less = 1 - np.exp(-at) * (1 + at) < p
        low, high = np.where(less, at, low), np.where(less, high, at)
    return ((low + high) / 2).astype(np.float32)


def _variates(term: np.ndarray, samples: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """r, b and ln c of each term (rows) and sample, the same in every process."""
    h = (term[:, None] ^ _salts(samples)[None, :]) * _MIX
    h ^= h >> np.uint64(29)
    h *= _PAIR
    h ^= h >> np.uint64(32)
    parts = h.view(np.uint16).reshape(len(term), samples, 4)
    r = _gamma_quantiles()[parts[:, :, 0]]
    b = parts[:, :, 1].astype(np.float32)
    b *= np.float32(1 / 65536)
    # c is the sum of two exponentials, so that its least values are as fine as its others
    c = parts[:, :, 2].astype(np.float32)
    c += np.float32(0.5)
    other = parts[:, :, 3].astype(np.float32)
    other += np.float32(0.5)
    c *= other
    c *= np.float32(2.0**-32)
    np.log(c, out=c)
    np.negative(c, out=c)
    np.log(c, out=c)
    return r, b, c


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(31))) * _MIX
    return h ^ (h >> np.uint64(29))


def terms(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Distinct term values and their weights."""
    words = text.lower().split()
    n = len(words)
    h = np.fromiter(map(_words.__getitem__, words), np.uint64, n)
    found = _mixed(h[:-1] * _PAIR + (h[1:] ^ (h[1:] >> np.uint64(7)))) if n > 1 else _mixed(h)
    if n < SHORT_WORDS:
        chars = text.lower()
        extra = [_words[chars[i : i + 3]] ^ 0x5BD1E995 for i in range(max(1, len(chars) - 2))] if chars else []
        found = np.concatenate([found, _mixed(np.array(extra, np.uint64))])
    return np.unique(found, return_counts=True)


def signature(text: str | None, samples: int = SAMPLES) -> np.ndarray:
    """16-bit samples; all zero for an empty text, never all zero for another."""
    if not text:
        return np.zeros(samples, np.uint16)
    term, weight = terms(text)
    least = np.full(samples, np.inf, np.float32)
    chosen, level = np.zeros(samples, np.uint64), np.zeros(samples, np.uint64)
    every = np.arange(samples)
    for at in range(0, len(term), SLICE):
        part, w = term[at : at + SLICE], weight[at : at + SLICE]
        r, b, log_a = _variates(part, samples)
        # ln a = ln c - r (t - b) - r; t is 0 for a term that occurs once, since 0 <= b < 1
        many = np.flatnonzero(w > 1)
        t = np.floor(np.log(w[many]).astype(np.float32)[:, None] / r[many] + b[many])
        b -= np.float32(1)
        b *= r
        log_a += b
        log_a[many] -= r[many] * t
        best = np.argmin(log_a, axis=0)
        a = log_a[best, every]
        less = a < least
        least[less], chosen[less] = a[less], part[best[less]]
        place = np.full(len(part), -1)
        place[many] = np.arange(len(many))
        row = place[best]
        level[less] = 0
        held = np.flatnonzero(less & (row >= 0))
        level[held] = t[row[held], held].astype(np.int64).astype(np.uint64)
    return ((_mixed(chosen * _PAIR + level + np.uint64(1)) >> np.uint64(48)) | np.uint64(1)).astype(np.uint16)


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    """Share of equal samples: an estimate of the generalised Jaccard similarity."""
    return float(np.count_nonzero(a == b)) / len(a)


def _hex(signature: np.ndarray) -> str:
    return signature.astype(">u2").tobytes().hex()


def fingerprint_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", samples: int = SAMPLES) -> DataFrame:
    """doc_id, fingerprint (four hex digits a sample) of every row; null text is empty.

    Rows are worked on alone: null ids, repeated rows and texts of any length are as any other."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([_hex(signature(x.as_py(), samples)) for x in batch.column(1)], pa.string())], names=["doc_id", "fingerprint"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "doc_id long, fingerprint string")


def map_with_next(docs: DataFrame, function: Callable[[tuple, tuple], tuple], schema: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """function(row, next row) over all rows in descending id order, the last one's next
    being the first; rows are (doc_id, text). Null ids come last; equal ids by text hash.

    Ids are cut into ranges of about equal counts and dealt by range; the head of each
    range is sent a second time, to the range before it, so no row crosses tasks."""
    spark = docs.sparkSession
    keys = docs.select(order_key(id_col).alias("k"))
    n = keys.count()
    if not n:
        return spark.createDataFrame([], schema)
    bounds = key_bounds(keys, "k", bucket_count(n, 4 * partitions(spark)))
    heads = keys.withColumn("b", bucket_of(F.col("k"), bounds)).groupBy("b").agg(F.max("k").alias("k")).orderBy("b").collect()  # one row per range
    # A head is the next row of the range above it; the first range's next is the last head.
    head, above = [None] * (len(bounds) + 1), [None] * (len(bounds) + 1)
    for i, x in enumerate(heads):
        head[x["b"]], above[x["b"]] = x["k"], heads[(i + 1) % len(heads)]["b"]
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"), order_key(id_col).alias("k"), bucket_of(order_key(id_col), bounds).alias("at"))
    here = F.struct(F.col("at").alias("b"), F.lit(0).alias("copy"))
    there = F.struct(F.get(F.array(*[F.lit(x).cast("int") for x in above]), "at").alias("b"), F.lit(1).alias("copy"))
    is_head = F.get(F.array(*[F.lit(x).cast("long") for x in head]), "at") == F.col("k")
    dealt = rows.select("doc_id", "text", "k", F.inline(F.when(is_head, F.array(here, there)).otherwise(F.array(here))))
    ordered = dealt.repartition(partitions(spark), "b").sortWithinPartitions("b", "copy", F.desc("k"), F.xxhash64("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, names = None, None
        out: list[tuple] = []
        for batch in batches:
            names = names or schema_names
            ids, bs, cs = (batch.column(i).to_pylist() for i in (0, 2, 3))
            for i, text in enumerate(batch.column(1)):
                row = (bs[i], (ids[i], text.as_py()))
                if held is not None and held[0] == row[0]:
                    out.append(function(held[1], row[1]))
                held = None if cs[i] else row
                if cs[i] or len(out) >= 1000:
                    if out:
                        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), types, strict=True)], names=names)
                    out = []
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), types, strict=True)], names=names)

    from pyspark.sql.pandas.types import to_arrow_type
    from pyspark.sql.types import StructType

    fields = StructType.fromDDL(schema).fields
    schema_names, types = [f.name for f in fields], [to_arrow_type(f.dataType) for f in fields]
    return ordered.select("doc_id", "text", "b", "copy").mapInArrow(run, schema)


def edited_text(text: str | None, following: str | None) -> str:
    """The last third of the code points gives way to as many first ones of the next text."""
    text, k = text or "", len(text or "") // 3
    return text[: len(text) - k] + (following or "")[:k]
