"""Language identification by segmentation-marginalised unigrams.

Each language has a probability for every piece of a fixed public vocabulary. A word's probability in a
language is the sum over all ways to cut it into pieces of the product of their probabilities, by a
forward pass over its characters; a text's is the product over its words, as no piece crosses a word.
Probabilities are learned by expectation-maximisation over counts of (language, word): each round sums,
in Spark, the expected number of uses of each piece over all segmentations, and normalises.

The forward pass runs over many words at once in numpy; a worker remembers recent words' scores, up to
CACHE_ENTRIES. Fitting uses at most about fit_rows labelled rows, a documented bound, picked by a hash.

A posterior among the learned languages says nothing of a text in none of them, so a background that holds
every piece equally likely takes part too: `margin` is by how many nats a character the best language beats
it. Below 0 no learned language explains the text better than the bare vocabulary does.

Defined results: null text or text without a letter is `und` with score and margin 0; equal texts get equal
answers; words over MAX_WORD characters count as several, in fitting as in prediction; lang, source and
doc_id play no part in a prediction; with no labelled rows every text is `und`; an empty table gives an empty
table; columns named like the results are replaced.
"""

from __future__ import annotations

import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sheetgraph.llm._shared import Scratch, held, map_arrow, prepare, runs_of, texts_of, without

MARK = "▁"
MAX_WORD = 32
CACHE_ENTRIES = 400_000
UNKNOWN = 1e-7
LETTER = re.compile(r"[^\W\d_]")
BASE = np.uint64(0x9E3779B97F4A7C15)


class Pieces:
    """Finds the pieces among the substrings of many words: a bitmap in front of a sorted hash table."""

    def __init__(self, model_path: str):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=model_path)
        n = sp.get_piece_size()
        self.names = [sp.id_to_piece(i) for i in range(n) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i))]
        self.size = len(self.names)
        self.longest = max(map(len, self.names))
        with np.errstate(over="ignore"):
            h = np.array([self._hash(x) for x in self.names], dtype=np.uint64)
        self.order = np.argsort(h)
        self.hashes = h[self.order]
        self.bits = np.zeros(1 << 22, dtype=bool)
        self.bits[h >> np.uint64(42)] = True

    @staticmethod
    def _hash(text: str) -> np.uint64:
        h = np.uint64(0)
        for c in text:
            h = (h + np.uint64(ord(c) + 1)) * BASE
        return h

    def find(self, h: np.ndarray) -> np.ndarray:
        """Piece number of each hash, self.size where there is none."""
        out = np.full(len(h), self.size, dtype=np.int64)
        maybe = np.flatnonzero(self.bits[h >> np.uint64(42)])
        at = np.minimum(np.searchsorted(self.hashes, h[maybe]), self.size - 1)
        hit = self.hashes[at] == h[maybe]
        out[maybe[hit]] = self.order[at[hit]]
        return out

    def edges(self, words: list[str]) -> list[list[np.ndarray]]:
        """For words of one length n: edges[i][l-1] holds, by word, the piece at [i, i+l), or size for none.

        A single character that is no piece gets number size + 1, the unknown one.
        """
        n = len(words[0])
        codes = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), dtype=np.uint32).reshape(len(words), n).astype(np.uint64) + np.uint64(1)
        out = []
        for i in range(n):
            h = np.zeros(len(words), dtype=np.uint64)
            row = []
            for j in range(i, min(n, i + self.longest)):
                h = (h + codes[:, j]) * BASE
                found = self.find(h)
                if j == i:
                    found[found == self.size] = self.size + 1
                row.append(found)
            out.append(row)
        return out


def by_length(words: list[str], most: int = 20_000):
    """Groups of positions of words that have one length."""
    lengths = np.array([len(w) for w in words])
    order = np.argsort(lengths, kind="stable")
    for group in np.split(order, np.flatnonzero(np.diff(lengths[order])) + 1):
        for k in range(0, len(group), most):
            if len(group):
                yield group[k : k + most]


def log_likelihoods(pieces: Pieces, table: np.ndarray, words: list[str]) -> np.ndarray:
    """Rows of log P(word | language). table: (size + 2) x languages, zero row for none, then the unknown's."""
    out = np.zeros((len(words), table.shape[1]))
    for group in by_length(words) if words else ():
        some = [words[k] for k in group]
        n = len(some[0])
        edges = pieces.edges(some)
        alphas = [np.ones((len(some), table.shape[1]))]
        scale = np.zeros_like(alphas[0])
        for j in range(1, n + 1):
            new = np.zeros_like(scale)
            for i in range(max(0, j - pieces.longest), j):
                found = edges[i][j - i - 1]
                if (found != pieces.size).any():
                    new += alphas[i] * table[found]
            alphas.append(new)
            if j % 8 == 0:  # all that later steps read is brought back near 1
                top = np.maximum(np.maximum.reduce(alphas[max(0, j - pieces.longest + 1) :]), 1e-300)
                for i in range(max(0, j - pieces.longest + 1), j + 1):
                    alphas[i] = alphas[i] / top
                scale += np.log(top)
            if j >= pieces.longest:
                alphas[j - pieces.longest] = None
        out[group] = np.log(np.maximum(alphas[n], 1e-300)) + scale
    return out


def expected_uses(pieces: Pieces, table: np.ndarray, words: list[str], langs: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Expected uses of each piece in each language, over all segmentations of the counted words."""
    out = np.zeros_like(table)
    for group in by_length(words, 5_000) if words else ():
        some, lang, count = [words[k] for k in group], langs[group], counts[group]
        n = len(some[0])
        edges = pieces.edges(some)
        p = [[table[e, lang] for e in row] for row in edges]
        alpha = np.zeros((n + 1, len(some)))
        beta = np.zeros((n + 1, len(some)))
        alpha[0] = beta[n] = 1
        for j in range(1, n + 1):
            for i in range(max(0, j - pieces.longest), j):
                alpha[j] += alpha[i] * p[i][j - i - 1]
        for i in range(n - 1, -1, -1):
            for step, q in enumerate(p[i], 1):
                beta[i] += q * beta[i + step]
        weight = count / np.maximum(alpha[n], 1e-300)
        for i in range(n):
            for step, q in enumerate(p[i], 1):
                np.add.at(out, (edges[i][step - 1], lang), alpha[i] * q * beta[i + step] * weight)
    return out


_pieces: dict[str, Pieces] = held("langid")


def pieces_of(path: str) -> Pieces:
    if path not in _pieces:
        _pieces[path] = Pieces(path)
    return _pieces[path]


def words_of(text: str) -> list[str]:
    """Lower-case words between white space, cut at MAX_WORD characters."""
    words = text.lower().split()
    if len(text) > MAX_WORD and max(map(len, words), default=0) > MAX_WORD:
        words = [w[k : k + MAX_WORD] for w in words for k in range(0, len(w), MAX_WORD)]
    return words


class Model:
    """Learned languages and the table of piece probabilities; a few MB for any corpus."""

    def __init__(self, path: str, langs: list[str], table: np.ndarray):
        self.path, self.langs, self.table = path, langs, table


def fit(docs: DataFrame, model_path: str, train: F.Column, fit_rows: int = 10_000, rounds: int = 3, lang: str = "lang", text: str = "text", key: str = "doc_id") -> Model:
    """Learn from rows where train holds and lang and text are not null; about fit_rows of them at most."""
    spark = docs.sparkSession
    prepare(spark)
    rows = docs.where(train & F.col(lang).isNotNull() & F.col(text).isNotNull())
    seen = rows.groupBy(F.col(lang).alias("lang")).count().collect()  # a row for each language
    langs = sorted(r["lang"] for r in seen)
    total = sum(r["count"] for r in seen)
    pieces = pieces_of(model_path)
    table = np.zeros((pieces.size + 2, max(1, len(langs))))
    table[: pieces.size] = 1 / pieces.size
    table[pieces.size + 1] = UNKNOWN
    if not langs:
        return Model(model_path, langs, table)
    share = min(1.0, fit_rows / total)
    picked = rows.where(F.pmod(F.xxhash64(key, F.lit("fit")), F.lit(1 << 20)) < int(share * (1 << 20)) + (share == 1.0))
    scratch = Scratch(spark, "langid")
    number = F.array_position(F.array(*[F.lit(x) for x in langs]), F.col(lang)) - 1

    def count():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            seen: Counter = Counter()
            for l, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                seen.update((l, w) for w in words_of(t))
            names = list(seen)
            return pa.RecordBatch.from_arrays([pa.array([l for l, _ in names], pa.int32()), pa.array([w for _, w in names], pa.string()), pa.array(list(seen.values()), pa.int64())], names=["lang", "word", "n"])

        return step

    words = map_arrow(picked.select(number.cast("int").alias("lang"), F.col(text).alias("text")), count, "lang int, word string, n long")
    words = scratch.keep(words.groupBy("lang", "word").agg(F.sum("n").alias("n")))
    for _ in range(rounds):
        now = table

        def make(now=now):
            def step(batch: pa.RecordBatch) -> pa.RecordBatch:
                some = [MARK + w for w in batch.column(1).to_pylist()]
                uses = expected_uses(pieces_of(model_path), now, some, batch.column(0).to_numpy(), batch.column(2).to_numpy())
                piece, language = np.nonzero(uses)
                return pa.RecordBatch.from_arrays([pa.array(piece.astype(np.int32)), pa.array(language.astype(np.int32)), pa.array(uses[piece, language])], names=["piece", "lang", "uses"])

            return step

        sums = map_arrow(words, make, "piece int, lang int, uses double").groupBy("piece", "lang").agg(F.sum("uses").alias("uses"))
        got = sums.toPandas()  # pieces x languages at most: the vocabulary is fixed, a language is some 100 KB
        table = np.zeros_like(now)
        table[got["piece"], got["lang"]] = got["uses"]
        table[: pieces.size] += 0.01  # no piece is impossible
        table[pieces.size] = 0
        table[pieces.size + 1] = 0
        table /= table.sum(axis=0)
        table[pieces.size + 1] = UNKNOWN
    scratch.drop(words)
    return Model(model_path, langs, table)


def _predictor(model: Model):
    """Languages and scores of a list of texts, with this task's memory of words."""
    pieces, cache = pieces_of(model.path), {}
    background = np.full((len(model.table), 1), 1 / pieces.size)
    background[pieces.size:, 0] = 0, UNKNOWN
    table = np.hstack([model.table, background])
    rows = [np.zeros((0, table.shape[1]))]

    def predict(texts: list[str]) -> tuple[list[str], list[float], list[float]]:
        lists = [words_of(t) for t in texts]
        if len(cache) > CACHE_ENTRIES:
            cache.clear()
            rows[:] = [rows[0][:0]]
        new = set()
        for u in lists:
            new.update(u)
        new = [w for w in new if w not in cache]
        if new:
            cache.update(zip(new, range(len(cache), len(cache) + len(new))))
            rows[:] = [np.vstack([rows[0], log_likelihoods(pieces, table, [MARK + w for w in new])])]
        langs, scores, margins = [], [], []
        for t, u in zip(texts, lists):
            if not model.langs or not LETTER.search(t):
                langs.append("und")
                scores.append(0.0)
                margins.append(0.0)
                continue
            total = rows[0][np.fromiter(map(cache.__getitem__, u), np.int64, len(u))].sum(axis=0)
            told, bare = total[:-1], total[-1]
            best = int(told.argmax())
            langs.append(model.langs[best])
            scores.append(float(1 / np.exp(told - told[best]).sum()))
            margins.append(float((told[best] - bare) / (sum(map(len, u)) + len(u))))
        return langs, scores, margins

    return predict


def predict(docs: DataFrame, model: Model, text: str = "text", lang_col: str = "lang_pred", score_col: str = "score", margin_col: str = "margin") -> DataFrame:
    """All columns of docs, then the language, its posterior probability and its margin over the background."""
    prepare(docs.sparkSession)
    docs = without(docs, lang_col, score_col, margin_col)
    names = docs.columns
    at = names.index(text)
    shared = docs.sparkSession.sparkContext.broadcast(model)  # a few MB, see Model

    def make():
        run = _predictor(shared.value)

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            langs, scores, margins = [], [], []
            for some in runs_of(texts_of(batch.column(at))):
                for all_, got in zip((langs, scores, margins), run(some)):
                    all_ += got
            told = [pa.array(langs, pa.string()), pa.array(scores, pa.float64()), pa.array(margins, pa.float64())]
            return pa.RecordBatch.from_arrays([*batch.columns, *told], names=[*names, lang_col, score_col, margin_col])

        return step

    added = [T.StructField(lang_col, T.StringType()), T.StructField(score_col, T.DoubleType()), T.StructField(margin_col, T.DoubleType())]
    return map_arrow(docs, make, T.StructType([*docs.schema.fields, *added]))


def held_out(key: str = "doc_id") -> F.Column:
    """The fold that is never learned from."""
    return F.coalesce(F.crc32(F.col(key).cast("string")) % 4 == 2, F.lit(False))
