"""Registered queries of the training-data operators and their SQL where it can be said."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from supplyrisk.llm import decontaminate, language_id, line_dedup, mixing, secrets, sharding, simhash, substring_dedup, toxicity, weighted_fingerprints
from supplyrisk.llm.common import table


def _fold(n: int) -> Column:
    return F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(n)), F.lit(0))


def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.find_overlaps(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op2_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    import hashlib

    from supplyrisk.llm.weighted_fingerprints import _hex, edited_text, likeness, map_with_next, signature

    before: dict = {}  # the next row's signature is its own in the call after

    def row(own: tuple, following: tuple) -> tuple:
        text, edited = own[1] or "", edited_text(own[1], following[1])
        mine = before[text] if text in before else signature(text)
        other, its = signature(edited), signature(following[1])
        before.clear()
        before[following[1] or ""] = its
        digest = hashlib.sha256(edited.encode("utf-8", "surrogatepass")).hexdigest()
        return own[0], len(text), digest, _hex(mine), _hex(other), likeness(mine, other), likeness(mine, its)

    return map_with_next(table(spark, sf_dir, "documents"), row, "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")


def op3_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = sharding.shard_documents(table(spark, sf_dir, "documents"), 16)
    return got.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", F.col("slot").cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))


def op4_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = language_id.fit(docs, train=_fold(3) != 1)
    return language_id.identify(docs, model).select("doc_id", (_fold(3) == 1).alias("held_out"), "lang_pred", "score")


def op5_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = substring_dedup.dedup_substrings(table(spark, sf_dir, "documents"), digest=True)
    return got.select("doc_id", "n_bytes", "n_removed", "n_spans", F.col("kept").cast("string").alias("kept_sha256"))


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = line_dedup.dedup_lines(table(spark, sf_dir, "documents"))
    return got.select("doc_id", "n_lines", "removed_chunks", "removed_lines", F.md5(F.col("text").cast("binary")).alias("kept_md5"))


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"), train=_fold(5) != 0)
    got = toxicity.score_toxicity(docs, model)
    return got.select("doc_id", (_fold(5) == 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_sources(table(spark, sf_dir, "documents"))


def op9_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = simhash.near_duplicates(table(spark, sf_dir, "documents"))
    return got.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def op10_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    spans = F.col("spans")
    base = F.filter(spans, lambda s: s["kind"].isin(*secrets.BASE_KINDS))
    kinds = F.transform(spans, lambda s: s["kind"])
    counts = [(F.size(kinds) - F.size(F.array_remove(kinds, k))).cast("long").alias(f"n_{k}") for k in secrets.BASE_KINDS]
    return secrets.scan_secrets(table(spark, sf_dir, "documents")).select("doc_id", *counts, F.sha2(secrets.joined_spans(base).cast("binary"), 256).alias("base_sha256"), secrets.joined_spans(spans).alias("spans"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_decontamination, op2_fingerprints, op3_sharding, op4_language_id, op5_suffix_dedup, op6_line_dedup, op7_toxicity, op8_mixing, op9_simhash, op10_secrets, pipeline)}

# --- SQL for DuckDB -----------------------------------------------------------------------

_MASKS = decontaminate.MASKS
_SPAN, _PENALTY, _LEAST, _FIFTHS, _SHORTEST = decontaminate.SPAN, decontaminate.PENALTY, decontaminate.MIN_SCORE, decontaminate.LEAST_SHARE, decontaminate.MIN_WORDS


def _leaks_sql() -> str:
    """Seeds are the masked words themselves; the best stretch is a running sum less its running minimum."""
    words = "list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\\p{L}\\p{N}]+'), lambda x: x <> '')"
    key = lambda w: " || '|' || ".join
    masked = lambda w: "unnest([" + ", ".join(f"'{m}|' || " + key(w)(f"{w}[k + {p + 1}]" for p in mask) for m, mask in enumerate(_MASKS)) + "])"
    seeds = lambda name, ident: f"SELECT {ident}, k, {masked('words')} AS seed FROM (SELECT {ident}, words, unnest(range(len(words) - {_SPAN - 1})) AS k FROM {name} WHERE len(words) >= {_SPAN}) UNION ALL SELECT {ident}, k, 'short|' || array_to_string(words[k + 1 : k + n], '|') FROM (SELECT {ident}, words, n, unnest(range(len(words) - n + 1)) AS k FROM {name}, short WHERE {'len(words) = n' if name == 'b' else 'len(words) >= n'})"
    return f"""WITH d AS MATERIALIZED (SELECT doc_id, {words} AS words FROM documents), b AS MATERIALIZED (SELECT item_id, {words} AS words FROM benchmark),
short AS MATERIALIZED (SELECT DISTINCT len(words) AS n FROM b WHERE len(words) BETWEEN {_SHORTEST} AND {_SPAN - 1}),
ds AS ({seeds('d', 'doc_id')}), bs AS ({seeds('b', 'item_id')}),
met AS MATERIALIZED (SELECT DISTINCT doc_id, item_id, ds.k - bs.k AS shift FROM ds JOIN bs USING (seed)),
each AS (SELECT doc_id, item_id, shift, d.words AS dw, b.words AS bw, unnest(range(greatest(0, -shift), least(len(b.words), len(d.words) - shift))) AS q FROM met JOIN d USING (doc_id) JOIN b USING (item_id)),
hit AS (SELECT doc_id, item_id, shift, len(dw) AS doc_words, len(bw) AS n, q, CASE WHEN bw[q + 1] = dw[q + shift + 1] THEN 1 ELSE 0 END AS same FROM each),
run AS (SELECT *, sum(CASE same WHEN 1 THEN 1 ELSE -{_PENALTY} END) OVER w AS s, sum(same) OVER w AS e FROM hit WINDOW w AS (PARTITION BY doc_id, item_id, shift ORDER BY q)),
low AS (SELECT *, coalesce(min(s) OVER v, 0) AS m0, coalesce(arg_min({{'q': q, 'e': e}}, s * 1000000 - q) OVER v, NULL) AS at0 FROM run WINDOW v AS (PARTITION BY doc_id, item_id, shift ORDER BY q ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
base AS (SELECT *, CASE WHEN m0 > 0 OR at0 IS NULL THEN 0 ELSE m0 END AS m, CASE WHEN m0 > 0 OR at0 IS NULL THEN greatest(0, -shift) ELSE at0.q + 1 END AS first, CASE WHEN m0 > 0 OR at0 IS NULL THEN 0 ELSE at0.e END AS e0 FROM low),
best AS (SELECT doc_id, item_id, shift, doc_words, n, s - m AS score, e - e0 AS same, first, q + 1 AS past FROM base QUALIFY row_number() OVER (PARTITION BY doc_id, item_id ORDER BY s - m DESC, shift, q) = 1)
SELECT doc_id, item_id, score::INT AS score, same::INT AS same, first::INT AS item_first, past::INT AS item_past, (first + shift)::INT AS doc_first, doc_words::INT AS doc_words FROM best WHERE score >= CASE WHEN n < {_SPAN} THEN n ELSE least({_LEAST}, ceil(n * {_FIFTHS} / 5)) END"""


_CRC = """crc AS MATERIALIZED (SELECT list(list_reduce(list_prepend(i, [0, 0, 0, 0, 0, 0, 0, 0]), lambda c, z: CASE WHEN c % 2 = 1 THEN xor(c // 2, 3988292384) ELSE c // 2 END) ORDER BY i) AS t FROM range(256) r(i))"""
_SHARD_SQL = f"""WITH {_CRC},
raw AS (SELECT doc_id, coalesce(text, '') AS text, hex(encode(coalesce(text, ''))) AS h FROM documents),
sized AS (SELECT doc_id, (len(h) // 2 + 1)::BIGINT AS size, xor(list_reduce(list_prepend(4294967295::BIGINT, list_transform(range(0, len(h) // 2), lambda i: ('0x' || substr(h, 2 * i + 1, 2))::BIGINT)), lambda c, b: xor(c // 256, t[xor(c % 256, b) + 1])), 4294967295)::BIGINT AS text_crc32 FROM raw, crc),
placed AS (SELECT *, sum(size) OVER w - size AS start, row_number() OVER w AS n, sum(size) OVER () AS total FROM sized WINDOW w AS (ORDER BY doc_id, text_crc32, size ROWS UNBOUNDED PRECEDING)),
cut AS (SELECT *, least(15, floor((start + size / 2) * 16 / total))::INT AS shard FROM placed)
SELECT doc_id, size, text_crc32, 'bytes' AS law, shard, (row_number() OVER (PARTITION BY shard ORDER BY n) - 1)::BIGINT AS slot, NULL::INT AS grown_shard FROM cut"""

_SUBSTRING_SQL = """WITH d AS MATERIALIZED (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
w AS MATERIALIZED (SELECT doc_id, p, substr(h, 2 * p + 1, 100) AS s FROM (SELECT doc_id, h, unnest(range(len(h) // 2 - 49)) AS p FROM d WHERE len(h) >= 100)),
f AS (SELECT s, min(doc_id) AS m FROM w GROUP BY s),
hit AS (SELECT doc_id, p FROM w JOIN f USING (s) WHERE m < doc_id),
cut AS (SELECT *, CASE WHEN p <= lag(p) OVER o + 50 THEN 0 ELSE 1 END AS fresh FROM hit WINDOW o AS (PARTITION BY doc_id ORDER BY p)),
span AS (SELECT doc_id, k, min(p) AS a, max(p) + 50 AS b FROM (SELECT *, sum(fresh) OVER (PARTITION BY doc_id ORDER BY p) AS k FROM cut) GROUP BY ALL),
piece AS (SELECT doc_id, a, b, coalesce(lag(b) OVER (PARTITION BY doc_id ORDER BY a), 0) AS before FROM span),
gone AS (SELECT doc_id, sum(b - a) AS n, count(*) AS spans, string_agg(substr(h, 2 * before + 1, 2 * (a - before)), '' ORDER BY a) || substr(any_value(h), (2 * max(b) + 1)::BIGINT) AS kept FROM piece JOIN d USING (doc_id) GROUP BY doc_id)
SELECT doc_id, (len(h) // 2)::BIGINT AS n_bytes, coalesce(n, 0)::BIGINT AS n_removed, coalesce(spans, 0)::BIGINT AS n_spans, sha256(unhex(coalesce(kept, h))) AS kept_sha256 FROM d LEFT JOIN gone USING (doc_id)"""

_LINES_SQL = f"""WITH d AS MATERIALIZED (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS lines FROM documents),
l AS (SELECT doc_id, lines, i, ('0x' || substr(md5(lines[i]), 1, 7))::BIGINT AS h FROM (SELECT doc_id, lines, unnest(range(1, len(lines) + 1)) AS i FROM d)),
m AS (SELECT doc_id, 0 AS i FROM d UNION ALL SELECT doc_id, i FROM (SELECT *, (h + coalesce(lag(h) OVER (PARTITION BY doc_id ORDER BY i), 0) * {line_dedup.ROLL}) % {line_dedup.MIXER} % {line_dedup.CHUNK_LINES} = 0 AS marked FROM l) WHERE marked),
a AS (SELECT doc_id, i FROM (SELECT *, row_number() OVER (PARTITION BY doc_id, island ORDER BY i) AS nth FROM (SELECT *, i - row_number() OVER (PARTITION BY doc_id ORDER BY i) AS island FROM m)) WHERE nth % 2 = 1),
g AS (SELECT doc_id, unnest(range(i, greatest(i, n - {line_dedup.MIN_LINES}) + 1, {line_dedup.MAX_LINES})) AS i FROM (SELECT doc_id, i, coalesce(lead(i) OVER (PARTITION BY doc_id ORDER BY i), len(lines)) AS n FROM a JOIN d USING (doc_id))),
e AS (SELECT DISTINCT doc_id, lines, i FROM (SELECT doc_id, i FROM g WHERE i > 0 UNION ALL SELECT doc_id, len(lines) FROM d) JOIN d USING (doc_id)),
c AS MATERIALIZED (SELECT doc_id, first, i AS past, array_to_string(lines[first + 1 : i], chr(10)) AS text FROM (SELECT *, coalesce(lag(i) OVER (PARTITION BY doc_id ORDER BY i), 0) AS first FROM e)),
r AS (SELECT *, past - first >= {line_dedup.MIN_LINES} AND trim(text) <> '' AND row_number() OVER (PARTITION BY text, past - first >= {line_dedup.MIN_LINES} ORDER BY doc_id, first) > 1 AS gone FROM c)
SELECT doc_id, max(past)::INT AS n_lines, count(*) FILTER (gone)::INT AS removed_chunks, coalesce(sum(past - first) FILTER (gone), 0)::INT AS removed_lines, md5(coalesce(string_agg(text, chr(10) ORDER BY first) FILTER (NOT gone), '')) AS kept_md5 FROM r GROUP BY doc_id"""

#: The others learn, hash or schedule in ways SQL cannot say; tests hold them against brute force.
ORACLES: dict[str, str] = {"op1_decontamination": _leaks_sql(), "op3_sharding": _SHARD_SQL, "op5_suffix_dedup": _SUBSTRING_SQL, "op6_line_dedup": _LINES_SQL}
