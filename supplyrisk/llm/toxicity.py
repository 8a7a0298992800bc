"""Toxicity by a weighted lexicon matched with Aho-Corasick.

Texts are folded first: lower case, look-alike letters to Latin, digits and signs that
stand for letters to those letters (in words that have a letter; a 1 is tried as i and as
l), invisible characters out. Terms (whole words or word
beginnings) carry weights; a hit inside an exception phrase does not count. The sum of
weights is divided by a slowly growing function of the text's length, damped, and a
logistic curve turns it to a score.

Weights are log odds of document frequency among labelled rows, over a sample of at most
about `SAMPLE_ROWS` labelled rows (a fixed hash of the id decides); a public seed lexicon
holds where labels say nothing. Everything else covers all rows.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Bound on labelled rows that the lexicon and the curve are fitted on.
SAMPLE_ROWS = 12_000
#: A learnt term needs this G-test value, this share of its documents toxic, and this share of toxic documents.
MIN_G, MIN_PRECISION, MIN_SHARE = 24.0, 2 / 3, 0.01
#: Lengths of word beginnings that are tried as terms.
STEMS = range(3, 11)
#: Terms whose counts a task holds before it passes them on.
COUNTED_TERMS = 100_000
#: Words of text per unit of the length norm.
NORM_WORDS = 400

# A public seed lexicon (whole words) and phrases in which a term is harmless.
SEED_TERMS = {
    "idiot": 3.0, "idiots": 3.0, "moron": 3.0, "stupid": 2.5, "scum": 3.0, "worthless": 2.0, "pathetic": 2.0, "loser": 2.5,
    "disgusting": 2.0, "trash": 1.5, "clown": 1.5, "imbecile": 3.0, "bastard": 3.0, "filthy": 1.5, "retard": 3.0,
    "asshole": 4.0, "bitch": 4.0, "fuck": 4.0, "fucking": 4.0, "shit": 3.5, "whore": 4.0,
    "idiota": 3.0, "estúpido": 3.0, "imbécil": 3.0, "basura": 1.5, "mierda": 3.5, "puta": 4.0, "cabrón": 3.5,
    "crétin": 3.0, "salaud": 3.5, "connard": 4.0, "merde": 3.5, "putain": 3.0, "débile": 2.5,
    "arschloch": 4.0, "scheiße": 3.5, "dummkopf": 3.0, "abschaum": 3.0, "trottel": 3.0, "hurensohn": 4.0,
}
EXCEPTIONS = (
    "trash can", "trash bin", "trash bag", "trash collection", "class clown fish", "clown fish", "clown college", "pond scum", "soap scum", "loser bracket", "sore loser rule", "not stupid", "shit happens",
    "cubo de basura", "bolsa de basura", "camión de basura", "recogida de basura", "basura orgánica", "basura espacial", "comida basura", "correo basura",
    "poisson clown", "clown de cirque", "nez de clown", "courant débile", "lumière débile",
    "clown im zirkus", "trottel der nacht", "abschaum beim kochen", "abschaum der suppe",
)
HOMOGLYPHS = {
    "а": "a", "е": "e", "о": "o", "р": "p", "с": "c", "у": "y", "х": "x", "і": "i", "ј": "j", "ѕ": "s", "к": "k", "м": "m", "т": "t", "в": "b", "н": "h",
    "α": "a", "ε": "e", "ο": "o", "ρ": "p", "ι": "i", "κ": "k", "ν": "v", "τ": "t", "υ": "u", "χ": "x", "ı": "i", "ɑ": "a", "ⅼ": "l", "ⅰ": "i", "ο": "o",
    "​": "", "‌": "", "‍": "", "⁠": "", "﻿": "", "­": "",
}
_FOLD = str.maketrans(HOMOGLYPHS | {chr(0xFF21 + i): chr(97 + i) for i in range(26)} | {chr(0xFF41 + i): chr(97 + i) for i in range(26)})
# Digits and signs that stand for letters, each inside a word with a letter.
_SIGNS = {"0": "o", "2": "z", "3": "e", "4": "a", "5": "s", "6": "g", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "|": "l"}
_AS_I, _AS_L = (str.maketrans(_SIGNS | {"1": x, "!": x}) for x in "il")
_WORD = re.compile(r"[^\W\d_]+")
_FOREIGN = re.compile(r"[^\x00-\x7f]")
_SIGN = re.compile(r"[0-9@$!|]")
_SIGNED = re.compile(r"(?<![\w@$!|])[\w@$!|]*[0-9@$!|][\w@$!|]*")


def _one_reading(low: str, as_l: bool) -> str:
    table = _AS_L if as_l else _AS_I

    def read(m: re.Match) -> str:
        word = m[0]
        body = word.rstrip("!|")  # signs that end a word are not part of it
        return body.translate(table) + word[len(body) :] if _WORD.search(body) else word

    return _SIGNED.sub(read, low)


def folds(text: str) -> list[str]:
    """The folded text; a second one of the same length if a 1 or ! may be an l as well."""
    low = text.lower()
    if _FOREIGN.search(low):
        low = low.translate(_FOLD)
    if not _SIGN.search(low):
        return [low]
    first = _one_reading(low, False)
    if "1" not in low and "!" not in low:
        return [first]
    other = _one_reading(low, True)
    return [first] if other == first else [first, other]


def fold(text: str) -> str:
    return folds(text)[0]


@dataclass
class ToxicityModel:
    """words and stems: weight of a whole word or of a word's beginning. bias, slope: of the curve."""

    words: dict[str, float]
    stems: dict[str, float]
    bias: float = -2.0
    slope: float = 1.5
    exceptions: tuple[str, ...] = EXCEPTIONS
    _matcher: object = field(default=None, repr=False, compare=False)

    def __getstate__(self) -> dict:
        return self.__dict__ | {"_matcher": None}

    def matcher(self) -> object:
        if self._matcher is None:
            a = ahocorasick.Automaton()
            terms: dict[str, list] = {}
            for kind, group in (("stem", self.stems), ("word", self.words)):
                for term, w in group.items():
                    terms.setdefault(term, []).append((kind, len(term), w))
            for phrase in self.exceptions:
                terms.setdefault(phrase, []).append(("exception", len(phrase), 0.0))
            for term, what in terms.items():
                a.add_word(term, what)
            a.make_automaton()
            self._matcher = a if terms else False
        return self._matcher

    def weigh(self, text: str | None) -> float:
        """Log of one plus the sum of weights over the length norm; a word counts for its best term."""
        if not text or not (matcher := self.matcher()):
            return 0.0
        hits: dict[int, float] = {}
        tame: list[tuple[int, int]] = []
        readings = folds(text)
        for s in readings:
            for end, found in matcher.iter(s):
                for kind, size, w in found:
                    start = end - size + 1
                    if start and s[start - 1].isalpha():
                        continue
                    if kind != "stem" and end + 1 < len(s) and s[end + 1].isalpha():
                        continue
                    if kind == "exception":
                        tame.append((start, end))
                    else:
                        hits[start] = max(w, hits.get(start, -math.inf))
        if tame:  # one sweep over both in order
            tame.sort()
            at, reach = 0, -1
            for start in sorted(hits):
                while at < len(tame) and tame[at][0] <= start:
                    reach = max(reach, tame[at][1])
                    at += 1
                if start <= reach:
                    del hits[start]
        total = sum(hits.values())
        return math.log1p(max(0.0, total) / (1.0 + math.log1p(len(readings[0]) / (6.0 * NORM_WORDS)) / 4.0))

    def score(self, text: str | None) -> float:
        z = self.bias + self.slope * self.weigh(text)
        return 1.0 / (1.0 + math.exp(-max(-30.0, min(30.0, z))))


def _terms_of(text: str) -> set[str]:
    """Whole words end in a blank; word beginnings do not."""
    out = set()
    for w in set(_WORD.findall(fold(text))):
        out.add(w + " ")
        for k in STEMS:
            if len(w) > k:
                out.add(w[:k])
    return out


def _g_test(t: np.ndarray, c: np.ndarray, nt: int, nc: int) -> np.ndarray:
    total, n = t + c, nt + nc
    g = np.zeros(len(t))
    for seen, size in ((t, nt), (c, nc)):
        for k, e in ((seen, total * size / n), (size - seen, (n - total) * size / n)):
            with np.errstate(divide="ignore", invalid="ignore"):
                g += np.where(k > 0, k * np.log(np.maximum(k, 1e-12) / np.maximum(e, 1e-12)), 0.0)
    return 2 * g


def choose_terms(counts: list[tuple[str, int, int]], nt: int, nc: int) -> tuple[dict[str, float], dict[str, float]]:
    """Words and stems whose documents are toxic far above chance, the most telling first;
    a term that begins a chosen one, or begins with it, is left out."""
    if not counts or not nt or not nc:
        return {}, {}
    names = [x for x, _, _ in counts]
    t, c = (np.array([x[i] for x in counts], float) for i in (1, 2))
    g = _g_test(t, c, nt, nc)
    ok = (g >= MIN_G) & (t / (t + c) >= MIN_PRECISION) & (t / nt > c / nc) & (t >= MIN_SHARE * nt)
    weight = np.log((t + 0.5) / (nt + 1)) - np.log((c + 0.5) / (nc + 1))
    words: dict[str, float] = {}
    stems: dict[str, float] = {}
    begun: set[str] = set()
    for i in sorted(np.flatnonzero(ok), key=lambda i: (-round(g[i], 6), -len(names[i]), names[i])):
        term = names[i]
        if term in begun or any(term[:k] in stems for k in range(1, len(term))):
            continue
        begun.update(term[:k] for k in range(1, len(term) + 1))
        (words if term.endswith(" ") else stems)[term.strip()] = float(weight[i])
    return words, stems


def _fit_curve(x: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Logistic bias and slope by damped Newton steps, lightly held."""
    beta = np.array([-2.0, 1.0])
    design = np.stack([np.ones(len(x)), x], axis=1)
    hold = np.diag([1e-3, 1e-2])
    for _ in range(30):
        p = 1 / (1 + np.exp(-np.clip(design @ beta, -30, 30)))
        grad = design.T @ (y - p) - hold @ beta
        hess = (design * (p * (1 - p))[:, None]).T @ design + hold
        step = np.linalg.solve(hess, grad)
        beta = beta + step * min(1.0, 4.0 / (np.abs(step).max() + 1e-9))
        if np.abs(step).max() < 1e-6:
            break
    return float(beta[0]), float(max(beta[1], 0.05))


def fit(docs: DataFrame, labels: DataFrame, *, train=None, sample_rows: int = SAMPLE_ROWS, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic") -> ToxicityModel:
    """Model from labelled rows. train: a Column over the labels that says which to use.

    Rows with a null id or label are not used. With no labels of both kinds the seed
    lexicon and a fixed curve are used. The driver gets significant terms, a 0/1 label and
    a weight for each sampled row; both are bounded by sample_rows."""
    known = labels.select(F.col(id_col).cast("long").alias("doc_id"), F.col(label_col).cast("int").alias("label")).where("doc_id is not null and label in (0, 1)")
    if train is not None:
        known = known.where(train)
    known = known.groupBy("doc_id").agg(F.max("label").alias("label"))
    n = known.count()
    if n > sample_rows:
        known = known.where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < int(1_000_000 * sample_rows / n))
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).where("text is not null")
    sample = texts.join(F.broadcast(known), "doc_id")  # about sample_rows rows of two numbers
    sample = sample.dropDuplicates(["text"])  # copies of one text say nothing new

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[str, list[int]] = {}

        def flush() -> Iterator[pa.RecordBatch]:
            names = list(seen)
            for at in range(0, len(names), 10_000):
                part = names[at : at + 10_000]
                yield pa.RecordBatch.from_arrays([pa.array(part), pa.array([seen[x][1] for x in part], pa.int64()), pa.array([seen[x][0] for x in part], pa.int64())], names=["term", "t", "c"])
            seen.clear()

        for batch in batches:
            for text, y in zip(batch.column(0), batch.column(1).to_pylist(), strict=True):
                for term in (*_terms_of(text.as_py()), ""):  # "" counts the rows themselves
                    seen.setdefault(term, [0, 0])[y] += 1
                if len(seen) > COUNTED_TERMS:
                    yield from flush()
        yield from flush()

    counted = sample.select("text", "label").mapInArrow(count, "term string, t long, c long").groupBy("term").agg(F.sum("t").alias("t"), F.sum("c").alias("c"))
    got = {r["term"]: (r["t"], r["c"]) for r in counted.where(F.expr("t >= 4") & (F.col("t") >= MIN_PRECISION * (F.col("t") + F.col("c"))) | (F.col("term") == "")).collect()}
    nt, nc = got.pop("", (0, 0))
    words, stems = choose_terms([(x, *tc) for x, tc in got.items()], nt, nc)
    model = ToxicityModel(SEED_TERMS | words, stems)
    if not nt or not nc:
        return model

    def weigh(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array([model.weigh(x.as_py()) for x in batch.column(0)], pa.float64()), batch.column(1)], names=["x", "y"])

    pairs = sample.select("text", "label").mapInArrow(weigh, "x double, y int").collect()
    model.bias, model.slope = _fit_curve(np.array([p["x"] for p in pairs]), np.array([p["y"] for p in pairs], float))
    return model


def score_toxicity(docs: DataFrame, model: ToxicityModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, score (0 to 1) of every row. Null and empty texts weigh nothing and get the
    curve's lowest score; repeated rows repeat; other columns are not read. No shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([model.score(x.as_py()) for x in batch.column(1)], pa.float64())], names=["doc_id", "score"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "doc_id long, score double")


def drop_toxic(docs: DataFrame, model: ToxicityModel, at_least: float = 0.5, text_col: str = "text") -> DataFrame:
    """The rows whose score is below at_least, with their own columns only. Only the text goes
    to Python; null and empty texts get the curve's lowest score; repeated rows repeat."""

    @F.arrow_udf("double")
    def score(text: pa.Array) -> pa.Array:
        return pa.array([model.score(x.as_py()) for x in text], pa.float64())

    return docs.where(score(F.col(text_col).cast("string")) < at_least)
