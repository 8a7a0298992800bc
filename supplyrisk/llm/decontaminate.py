"""Benchmark decontamination with spaced seeds, in DataFrame functions alone.

Texts become words (runs of letters and digits, lower case). A mask looks at six of SPAN
neighbouring words and ignores the others, so a hit survives substitutions there. Seeds are
narrow rows; the hits of a text and a benchmark item become distinct diagonals (equal
shifts), and only texts with a diagonal are looked at again. Along a diagonal an equal word
scores 1 and a substituted one -PENALTY, and the best-scoring stretch must reach what the
item's length asks for: MIN_SCORE, but at most LEAST_SHARE of the item's words (rounded up).
Items of MIN_WORDS to SPAN - 1 words are searched for as a whole, without substitutions;
shorter ones are not searched for, since they cannot be told from chance.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from supplyrisk.llm.common import stage

# Word places that each mask looks at.
MASKS = ((0, 1, 3, 4, 7, 8), (0, 2, 3, 5, 6, 8), (0, 1, 2, 5, 7, 8))
SPAN = 9
PENALTY = 2
MIN_SCORE = 10
#: Share of an item's words, in fifths, that is enough if the item is short.
LEAST_SHARE = 3
#: Items of fewer words are not searched for.
MIN_WORDS = 5
#: Seed rows of the benchmark, diagonals and texts to drop, up to which they are sent to every
#: executor (about 30 bytes each).
BROADCAST_SEEDS = 2_000_000
NON_WORD = r"[^\p{L}\p{N}]+"


def word_hashes(text: Column) -> Column:
    """Hash of each word; a null text has none."""
    words = F.array_remove(F.split(F.lower(F.coalesce(text, F.lit(""))), NON_WORD), "")
    return F.transform(words, lambda w: F.xxhash64(w))


def needed(words: Column, min_score: int = MIN_SCORE) -> Column:
    """Score that an item of so many words asks for."""
    return F.when(words < SPAN, words).otherwise(F.least(F.lit(min_score), F.ceil(words * LEAST_SHARE / 5))).cast("int")


def _seeds(rows: DataFrame, keep: list[str], lengths: list[int]) -> DataFrame:
    """A row for each place and mask: the columns to keep, `at`, `seed`. rows has `words`.

    lengths: of short items, whose seeds are stretches of all their words."""

    def places(span: int) -> Column:
        return F.when(F.size("words") >= span, F.sequence(F.lit(0), F.size("words") - span)).otherwise(F.array().cast("array<int>"))

    def seed(kind: int, mask: tuple[int, ...]) -> Column:
        return F.xxhash64(F.lit(kind), *[F.get("words", F.col("at") + p) for p in mask])

    at = rows.select(*keep, "words", F.explode(places(SPAN)).alias("at"))
    out = at.select(*keep, "at", F.explode(F.array(*[seed(m, mask) for m, mask in enumerate(MASKS)])).alias("seed"))
    for n in lengths:
        at = rows.select(*keep, "words", F.explode(places(n)).alias("at"))
        out = out.unionAll(at.select(*keep, "at", seed(-n, tuple(range(n))).alias("seed")))
    return out


def best_stretch(words: Column, item: Column, shift: Column) -> Column:
    """Best-scoring stretch of item against words on a diagonal: score, first and past-last
    item word, equal words. Earliest best; words beyond either end do not exist."""
    start = F.greatest(F.lit(0), -shift)
    length = F.least(F.size(item) - start, F.size(words) - (shift + start))
    equal = F.zip_with(F.slice(item, start + 1, length), F.slice(words, shift + start + 1, length), lambda x, y: x == y)
    zero = F.lit(0)
    # at, running score and its start and equal words; then the best of them
    names = ("at", "score", "first", "same", "best", "best_first", "best_past", "best_same")
    begin = F.struct(start.alias("at"), *[zero.alias(x) for x in names[1:]])

    def step(a: Column, hit: Column) -> Column:
        fresh = a["score"] <= 0
        score = F.when(fresh, 0).otherwise(a["score"]) + F.when(hit, 1).otherwise(-PENALTY)
        first = F.when(fresh, a["at"]).otherwise(a["first"])
        same = F.when(fresh, 0).otherwise(a["same"]) + F.when(hit, 1).otherwise(0)
        better = score > a["best"]
        new = (a["at"] + 1, score, first, same, F.greatest(score, a["best"]), F.when(better, first).otherwise(a["best_first"]), F.when(better, a["at"] + 1).otherwise(a["best_past"]), F.when(better, same).otherwise(a["best_same"]))
        return F.struct(*[c.alias(x) for c, x in zip(new, names, strict=True)])

    return F.aggregate(equal, begin, step, lambda a: F.struct(a["best"].alias("score"), a["best_first"].alias("first"), a["best_past"].alias("past"), a["best_same"].alias("same")))


def _text_key(text: Column) -> list[Column]:
    """128 bits of a text; null is empty."""
    text = F.coalesce(text, F.lit(""))
    return [F.xxhash64(text).alias("__h"), F.xxhash64(text, F.lit(1)).alias("__g")]


def _verified(docs: DataFrame, benchmark: DataFrame, id_col: str, text_col: str, item_col: str, item_text_col: str, min_score: int) -> DataFrame:
    """doc_id, __h, __g (of the text), item_id, shift, doc_words and b (best stretch) of each
    diagonal that reaches its item's score; a row for each row of docs."""
    items = benchmark.select(F.col(item_col).cast("long").alias("item_id"), word_hashes(F.col(item_text_col)).alias("words")).where(F.size("words") >= MIN_WORDS)
    lengths = [r["n"] for r in items.where(F.size("words") < SPAN).select(F.size("words").alias("n")).distinct().orderBy("n").collect()]  # a few
    whole = _seeds(items.where(F.size("words") >= SPAN), ["item_id"], [])
    for n in lengths:
        whole = whole.unionAll(_seeds(items.where(F.size("words") == n), ["item_id"], [n]))
    seeds = stage(whole.withColumnRenamed("at", "item_at"), "leak-seeds")
    own = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    rows = own.select(*_text_key(F.col("text")), word_hashes(F.col("text")).alias("words"))
    small = seeds.count() <= BROADCAST_SEEDS
    met = _seeds(rows, ["__h", "__g"], lengths).join(F.broadcast(seeds) if small else seeds, "seed")
    diagonals = stage(met.select("__h", "__g", "item_id", (F.col("at") - F.col("item_at")).alias("shift")).distinct(), "leak-diagonals")
    few = diagonals.count() <= BROADCAST_SEEDS
    again = own.select("doc_id", "text", *_text_key(F.col("text"))).join(F.broadcast(diagonals) if few else diagonals, ["__h", "__g"])
    item = items.select("item_id", F.col("words").alias("item"))
    both = again.join(F.broadcast(item) if small else item, "item_id").withColumn("words", word_hashes(F.col("text")))
    scored = both.select("doc_id", "__h", "__g", "item_id", "shift", F.size("words").alias("doc_words"), needed(F.size("item"), min_score).alias("least"), best_stretch(F.col("words"), F.col("item"), F.col("shift")).alias("b"))
    return scored.where(F.col("b.score") >= F.col("least")).drop("least")


def find_overlaps(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", min_score: int = MIN_SCORE) -> DataFrame:
    """The best overlap of each document and benchmark item that share one.

    Columns: doc_id, item_id, score, same (equal words), item_first, item_past, doc_first
    (word places, from 0), doc_words. Of rows that share an id (null ids too) the best counts,
    then the smallest shift, then the longest text; null texts have no words; items of fewer
    than MIN_WORDS words are not searched for; repeated items count once each id. Texts of any
    length are taken whole: what is exploded is two hashes a place. The benchmark side is sent
    to every executor after its size is counted, else both sides are dealt by seed (Spark then
    splits seeds that are too frequent); so are the diagonals found."""
    scored = _verified(docs, benchmark, id_col, text_col, item_col, item_text_col, min_score)
    best = F.max_by(F.struct("b", "shift", "doc_words"), F.struct(F.col("b.score"), -F.col("shift"), "doc_words")).alias("x")
    return scored.groupBy("doc_id", "item_id").agg(best).select("doc_id", "item_id", F.col("x.b.score").alias("score"), F.col("x.b.same").alias("same"), F.col("x.b.first").alias("item_first"), F.col("x.b.past").alias("item_past"), (F.col("x.b.first") + F.col("x.shift")).alias("doc_first"), F.col("x.doc_words").alias("doc_words"))


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", min_score: int = MIN_SCORE) -> DataFrame:
    """The rows whose text has no overlap, with their own columns; ids play no part.

    Leaked texts are known by 128 bits. Texts are not shuffled unless their list passes
    BROADCAST_SEEDS."""
    leaked = stage(_verified(docs, benchmark, id_col, text_col, item_col, item_text_col, min_score).select("__h", "__g").distinct(), "leaked")
    if leaked.count() <= BROADCAST_SEEDS:
        leaked = F.broadcast(leaked)
    h, g = _text_key(docs[text_col].cast("string"))
    return docs.join(leaked, (h == leaked["__h"]) & (g == leaked["__g"]), "left_anti")
