"""Language identification by segmentation-marginalised unigrams.

Each language has a probability for every piece of a fixed public vocabulary. The
probability of a word is the sum over all ways to cut it into pieces, by the forward
algorithm; words are independent, so a text's log probability is a sum over its words and
each distinct word is computed once per batch of work. Piece probabilities come from a
bounded sample of labelled rows by expectation maximisation over all segmentations.

Words are runs of letters in lower case after a start mark; other characters say nothing.
Runs of over MAX_WORD letters are cut into blocks of that length.
"""

from __future__ import annotations

import os
import re
from collections import Counter, defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from supplyrisk.llm.common import Staged

#: Where the public vocabulary lies; only the driver reads it.
VOCABULARY = "/opt/tokenizers/piece_bpe_32k.model"
#: Bound on labelled rows per language that probabilities are learnt from.
SAMPLE_ROWS_PER_LANGUAGE = 500
EM_ROUNDS = 3
MAX_WORD = 32
#: The start mark and a whole word; longer pieces can have no part in a segmentation.
MAX_PIECE = MAX_WORD + 1
START = "▁"
#: Words after which more text no longer sharpens the score.
SCORE_WORDS = 20
_WORD = re.compile(r"[^\W\d_]+")
_CACHE_WORDS = 300_000
#: Words worked on at once, and texts split at once.
_WORDS_AT_ONCE, _TEXTS_AT_ONCE = 10_000, 512


def load_pieces(path: str = VOCABULARY) -> list[str]:
    """Distinct lower-case letter pieces of the vocabulary, sorted."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=os.fspath(path))
    raw = (sp.id_to_piece(i).lower() for i in range(sp.get_piece_size()) if not sp.is_control(i) and not sp.is_byte(i) and not sp.is_unknown(i))
    return sorted({p for p in raw if 0 < len(p) <= MAX_PIECE and (p.lstrip(START).isalpha() or p == START)})


class Trie:
    """Transitions over the vocabulary; state 0 is dead, 1 the root.

    Characters of longer pieces have a dense table. The many others (one-character pieces
    of large scripts) only leave the root, for a state of their own without a way on."""

    def __init__(self, pieces: list[str]):
        self.pieces = pieces
        inner = sorted({c for p in pieces if len(p) > 1 for c in p})
        outer = sorted({p for p in pieces if len(p) == 1} - set(inner))
        self.width = len(inner) + 1
        self.code = {c: i + 1 for i, c in enumerate(inner + outer)}
        ways: list[dict[int, int]] = [{}, {}]
        piece_at = [0, 0]
        late = []
        for number, p in enumerate(pieces, 1):
            if len(p) == 1 and self.code[p] >= self.width:
                late.append((self.code[p], number))
                continue
            at = 1
            for c in p:
                k = self.code[c]
                if k not in ways[at]:
                    ways[at][k] = len(ways)
                    ways.append({})
                    piece_at.append(0)
                at = ways[at][k]
            piece_at[at] = number
        self.step = np.zeros((len(ways), self.width), np.int32)
        for at, out in enumerate(ways):
            for k, to in out.items():
                self.step[at, k] = to
        self.first = np.zeros(len(self.code) + 1, np.int32)
        self.first[: self.width] = self.step[1]
        for n, (k, number) in enumerate(late, len(ways)):
            self.first[k] = n
            piece_at.append(number)
        self.piece = np.array(piece_at, np.int32)

    def walk(self, codes: np.ndarray, at: int) -> Iterator[np.ndarray]:
        """Piece number (0: none) of each word's characters at..at + k, for k = 0, 1, ..."""
        state = self.first[codes[:, at]]
        yield self.piece[state]
        for k in range(1, min(MAX_PIECE, codes.shape[1] - at)):
            code = codes[:, at + k]
            on = (state < len(self.step)) & (code < self.width)
            state = np.where(on, self.step[np.where(on, state, 0), np.where(on, code, 0)], 0)
            if not state.any():
                return
            yield self.piece[state]

    def encode(self, words: list[str], width: int) -> np.ndarray:
        get = self.code.get
        flat = [get(c, 0) for w in words for c in START + w]
        return np.array(flat, np.int32).reshape(len(words), width)


def _by_length(words: list[str]) -> Iterator[tuple[int, np.ndarray]]:
    sizes = np.fromiter(map(len, words), np.int64, len(words))
    for n in np.unique(sizes):
        at = np.flatnonzero(sizes == n)
        for k in range(0, len(at), _WORDS_AT_ONCE):
            yield int(n) + 1, at[k : k + _WORDS_AT_ONCE]


def forward(trie: Trie, codes: np.ndarray, probs: np.ndarray, unknown: float) -> np.ndarray:
    """alpha[i, j]: sum over segmentations of the first j characters, for each language."""
    n, length = codes.shape
    alpha = np.zeros((length + 1, n, probs.shape[1]))
    alpha[0] = 1.0
    for i in range(length):
        here = alpha[i]
        alpha[i + 1] += here * unknown  # a character that no piece explains
        for k, piece in enumerate(trie.walk(codes, i)):
            if piece.any():
                alpha[i + k + 1] += here * probs[piece]
    return alpha


def expected_counts(trie: Trie, codes: np.ndarray, weights: np.ndarray, probs: np.ndarray, unknown: float, into: np.ndarray) -> None:
    """Add each piece's expected uses over all segmentations (weights: words by language)."""
    n, length = codes.shape
    alpha = forward(trie, codes, probs, unknown)
    beta = np.zeros_like(alpha)
    beta[length] = 1.0
    for i in range(length - 1, -1, -1):
        beta[i] += beta[i + 1] * unknown
        for k, piece in enumerate(trie.walk(codes, i)):
            beta[i] += probs[piece] * beta[i + k + 1]
    scale = weights / np.maximum(alpha[length], 1e-300)
    for i in range(length):
        for k, piece in enumerate(trie.walk(codes, i)):
            used = np.flatnonzero(piece)
            np.add.at(into, piece[used], alpha[i][used] * probs[piece[used]] * beta[i + k + 1][used] * scale[used])


def words_of(text: str) -> list[str]:
    words = _WORD.findall(text.lower())
    if any(len(w) > MAX_WORD for w in words):
        words = [w[i : i + MAX_WORD] for w in words for i in range(0, len(w), MAX_WORD)]
    return words


@dataclass
class LanguageModel:
    languages: list[str]
    pieces: list[str]
    #: Row 0 is "no piece" (zero), then one row per piece; a column per language.
    probs: np.ndarray
    unknown: float = 1e-7
    _trie: Trie | None = field(default=None, repr=False, compare=False)
    _seen: dict = field(default_factory=dict, repr=False, compare=False)
    _table: np.ndarray | None = field(default=None, repr=False, compare=False)

    def __getstate__(self) -> dict:
        return self.__dict__ | {"_trie": None, "_seen": {}, "_table": None}

    def word_logs(self, words: list[str]) -> np.ndarray:
        if self._trie is None:
            self._trie = Trie(self.pieces)
        out = np.zeros((len(words), len(self.languages)))
        for width, at in _by_length(words):
            codes = self._trie.encode([words[i] for i in at], width)
            out[at] = np.log(np.maximum(forward(self._trie, codes, self.probs, self.unknown)[width], 1e-300))
        return out

    def predict(self, texts: list[str | None]) -> list[tuple[str, float]]:
        """Language and score of each text; ("und", 0.0) where no letter is found."""
        if not self.languages:
            return [("und", 0.0)] * len(texts)
        if len(self._seen) > _CACHE_WORDS:
            self._seen = {}
        split = [words_of(t) if t else [] for t in texts]
        new = list({w for ws in split for w in ws} - self._seen.keys())
        if new:
            n = len(self._seen)
            if self._table is None or n + len(new) > len(self._table):
                grown = np.zeros((max(2 * (n + len(new)), 65_536), len(self.languages)))
                grown[:n] = 0 if self._table is None else self._table[:n]
                self._table = grown
            self._table[n : n + len(new)] = self.word_logs(new)
            self._seen.update(zip(new, range(n, n + len(new)), strict=True))
        out, get = [], self._seen.__getitem__
        for ws in split:
            if not ws:
                out.append(("und", 0.0))
                continue
            total = self._table[np.fromiter(map(get, ws), np.int64, len(ws))].sum(axis=0)
            best = int(np.argmax(total))
            z = (total - total[best]) * min(1.0, SCORE_WORDS / len(ws))
            out.append((self.languages[best], float(1.0 / np.exp(z).sum())))
        return out


def fit(docs: DataFrame, *, train: Column | None = None, rows_per_language: int = SAMPLE_ROWS_PER_LANGUAGE, vocabulary: str = VOCABULARY, lang_col: str = "lang", id_col: str = "doc_id", text_col: str = "text") -> LanguageModel:
    """Model from rows with a language (train: a Column over doc_id that says which).

    The sample takes about rows_per_language rows of each language by a fixed hash of the
    id, whole texts. Rows with null text or language are not used; with no rows at all
    the model predicts "und"."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"), F.col(lang_col).cast("string").alias("lang")).where("lang is not null and text is not null")
    if train is not None:
        rows = rows.where(train)
    sizes = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    languages, pieces = sorted(sizes), load_pieces(vocabulary)
    model = LanguageModel(languages, pieces, np.zeros((len(pieces) + 1, len(languages))))
    if not languages:
        return model
    share = F.create_map(*[F.lit(x) for lang in languages for x in (lang, int(min(1.0, rows_per_language / sizes[lang]) * 1_000_000))])
    sample = rows.where(F.pmod(F.xxhash64(F.coalesce("doc_id", F.lit(0)), F.lit(7)), F.lit(1_000_000)) < share[F.col("lang")])

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[str, Counter] = defaultdict(Counter)
        for batch in batches:
            for text, lang in zip(batch.column(0), batch.column(1).to_pylist(), strict=True):
                seen[lang].update(words_of(text.as_py()))
        for lang, counts in seen.items():
            words = list(counts)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(words), pa.string()), pa.array(words, pa.string()), pa.array([counts[w] for w in words], pa.int64())], names=["lang", "word", "n"])

    # Damped counts: a word repeated thousands of times should not own the model.
    counted = sample.select("text", "lang").mapInArrow(split, "lang string, word string, n long").groupBy("word", "lang").agg(F.sqrt(F.sum("n").cast("double")).alias("n"))
    words = Staged(counted, "language-words")
    number = {lang: i for i, lang in enumerate(languages)}
    probs = np.full((len(pieces) + 1, len(languages)), 1.0 / len(pieces))
    probs[0] = 0.0

    for _ in range(EM_ROUNDS):

        def expect(batches: Iterator[pa.RecordBatch], probs: np.ndarray = probs) -> Iterator[pa.RecordBatch]:
            trie, into = Trie(pieces), np.zeros(probs.shape)
            for batch in batches:
                lang, own = (batch.column(i).to_pylist() for i in (0, 1))
                n = batch.column(2).to_numpy()
                for width, at in _by_length(own):
                    weights = np.zeros((len(at), len(number)))
                    weights[np.arange(len(at)), [number[lang[i]] for i in at]] = n[at]
                    expected_counts(trie, trie.encode([own[i] for i in at], width), weights, probs, model.unknown, into)
            piece, k = np.nonzero(into)
            yield pa.RecordBatch.from_arrays([pa.array(piece.astype(np.int64)), pa.array(k.astype(np.int64)), pa.array(into[piece, k])], names=["piece", "k", "n"])

        got = words.df.select("lang", "word", "n").mapInArrow(expect, "piece long, k long, n double").groupBy("piece", "k").agg(F.sum("n").alias("n")).toPandas()
        uses = np.full(probs.shape, 0.05)
        uses[got["piece"], got["k"]] += got["n"]
        uses[0] = 0.0
        probs = uses / uses.sum(axis=0)
    words.drop()
    model.probs = probs
    return model


def identify(docs: DataFrame, model: LanguageModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, lang_pred, score of every row, from the text alone. Null text or no letter:
    `und`, 0. Repeated rows repeat; ties go to the first language by name. Texts are taken
    whole, whatever their length; other columns are not read. No shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, _TEXTS_AT_ONCE):
                part = batch.slice(at, _TEXTS_AT_ONCE)
                got = model.predict(part.column(1).to_pylist())
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([x for x, _ in got], pa.string()), pa.array([s for _, s in got], pa.float64())], names=["doc_id", "lang_pred", "score"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "doc_id long, lang_pred string, score double")
