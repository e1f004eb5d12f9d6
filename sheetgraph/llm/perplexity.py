"""Quality rules with n-gram perplexity: a modified Kneser-Ney model of characters inside words.

Spark counts the n-grams of every word of every document, by language; counts of lower orders are numbers
of different left neighbours, derived from the highest order's table. An n-gram is packed in 60 bits, 12 a
symbol: characters under ALPHABET are one symbol, all others two, so no two characters share one. The table
grows with the corpus as new n-grams turn up. Interpolated probabilities and back-off weights come out of
joins on those keys and are stored sorted by key; a worker loads the arrays of a language when it first
meets one of its documents, and searches them by bisection.

A document's perplexity is that of its words in its language's model, as bits a word. A language's band is
taken from the quartiles of that over all its documents, exact to 1/256 bit and so the same under any
partitioning, and wider for short texts; a document outside it, above or below, is rejected. Documents with a
null or empty language use the pooled name `und`. Documents are scored by a model that has counted them too.

Characters inside words, not words among words: of 24.9 million words in 0.1 GB of given documents 12.5
million pairs are different, so a table of pairs is half as large as the corpus (16 bytes a pair, 200 MB for
0.1 GB, in every worker, or a join of every word of the corpus). So the order of a text's words does not
count here.

Defined results: null or empty text has no word and fails the base rule; equal texts in one language get
equal verdicts; perplexity is null without a word, and in a language that the model has not counted, where
only the base rule decides; an empty table gives an empty table; columns named like the results are replaced.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sheetgraph.llm._shared import Scratch, file_system, map_arrow, prepare, runs_of, texts_of, unused, without

ORDER = 5
BITS = 12
#: Characters below this are one symbol; others two: LEAD + their upper bits, then the lower TRAIL bits.
ALPHABET = LEAD = 2_048
TRAIL = 10
START, END = (1 << BITS) - 1, (1 << BITS) - 2
CACHE_ENTRIES = 300_000
#: Words whose n-grams are in memory at once.
PIECE = 40_000
SYMBOLS = frozenset("#*$%&|<>")
SPACES = " \t\n\x0b\x0c\r"
#: Half-width of the band in interquartile ranges beyond the quartiles, the least such range in bits, the words
#: at which the band doubles, and bins of a bit in which quartiles are counted.
BAND_WIDTH, LEAST_RANGE, SHORT_WORDS, BINS = 4.0, 0.25, 50.0, 256
FEATURES = [("n_words", "long"), ("word_chars", "long"), ("n_symbols", "long"), ("n_dup_lines", "long"), ("n_repeat_words", "long")]


def symbols_of(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Keys of all highest-order n-grams of the words, with the word number of each."""
    raw = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), dtype=np.uint32).astype(np.int64)
    lengths = np.array([len(w) for w in words], dtype=np.int64)
    wide = raw >= ALPHABET
    if wide.any():
        places = np.arange(len(raw)) + np.cumsum(wide) - wide
        symbols = np.empty(len(raw) + int(wide.sum()), np.int64)
        symbols[places] = np.where(wide, LEAD + (raw >> TRAIL), raw)
        symbols[places[wide] + 1] = raw[wide] & ((1 << TRAIL) - 1)
        lengths += np.bincount(np.repeat(np.arange(len(words)), lengths)[wide], minlength=len(words))
        raw = symbols
    ends = np.cumsum(lengths + ORDER)  # each word: ORDER - 1 starts, its characters, one end
    flat = np.full(int(ends[-1]) if len(ends) else 0, START, dtype=np.int64)
    flat[ends - 1] = END
    inside = np.ones(len(flat), dtype=bool)
    inside[ends - 1] = False
    firsts = ends - lengths - ORDER
    for k in range(ORDER - 1):
        inside[firsts + k] = False
    flat[inside] = raw
    keys = np.zeros(len(flat), dtype=np.int64)
    for k in range(ORDER):
        keys[ORDER - 1 :] = (keys[ORDER - 1 :] << BITS) | flat[k : len(flat) - ORDER + 1 + k]
    event = np.ones(len(flat), dtype=bool)
    for k in range(ORDER - 1):
        event[firsts + k] = False
    return keys[event], np.repeat(np.arange(len(words)), lengths + 1)


def words_of(text: str) -> list[bytes]:
    """Words between the six ASCII white-space characters, as UTF-8."""
    return text.encode("utf-8", "surrogatepass").split()


def _language(name: str) -> F.Column:
    return F.coalesce(F.nullif(F.col(f"`{name}`"), F.lit("")), F.lit("und"))


def count_ngrams(docs: DataFrame, lang: str, text: str) -> DataFrame:
    """lang, key, n for every highest-order n-gram of every word, added up over the corpus."""
    src = docs.select(_language(lang).alias("lang"), F.col(text).alias("text")).where(F.col("text").isNotNull())

    def make():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            by_lang: dict[str, Counter] = {}
            langs, out = batch.column(0).to_pylist(), []
            for l, t in zip(langs, batch.column(1).to_pylist()):
                by_lang.setdefault(l, Counter()).update(words_of(t))
            for l, words in by_lang.items():
                times = np.fromiter(words.values(), np.int64, len(words))
                names = list(words)
                for k in range(0, len(names), PIECE):
                    keys, owner = symbols_of([w.decode("utf-8", "surrogatepass") for w in names[k : k + PIECE]])
                    found, at = np.unique(keys, return_inverse=True)
                    n = np.bincount(at, weights=times[k : k + PIECE][owner]).astype(np.int64)
                    out.append((l, found, n))
            return pa.RecordBatch.from_arrays(
                [
                    pa.array([l for l, k, _ in out for _ in range(len(k))], pa.string()),
                    pa.array(np.concatenate([k for _, k, _ in out]) if out else np.zeros(0, np.int64)),
                    pa.array(np.concatenate([n for *_, n in out]) if out else np.zeros(0, np.int64)),
                ],
                names=["lang", "key", "n"],
            )

        return step

    return map_arrow(src, make, "lang string, key long, n long").groupBy("lang", "key").agg(F.sum("n").alias("n"))


def _level(grams: DataFrame, order: int, lower: DataFrame | None) -> DataFrame:
    """lang, key, p, n, of one order: discounted share plus the context's weight times the lower order's p."""
    low = (1 << (BITS * (order - 1))) - 1
    grams = grams.withColumn("context", F.shiftright("key", BITS)).withColumn("suffix", F.col("key").bitwiseAND(F.lit(low)))
    of = grams.groupBy("lang").agg(*[F.count_if(F.col("n") == k).alias(f"n{k}") for k in (1, 2, 3, 4)])
    y = F.when(F.col("n1") > 0, F.col("n1") / (F.col("n1") + 2 * F.col("n2"))).otherwise(F.lit(0.5))

    def discount(k: int) -> F.Column:
        raw = F.lit(float(k)) - (k + 1) * y * F.col(f"n{k + 1}") / F.nullif(F.col(f"n{k}"), F.lit(0))
        # counts of counts of small corpora may give nonsense; then the usual absolute discounts
        return F.when(raw.between(0.05, k - 0.05), raw).otherwise(F.lit(0.25 + 0.25 * k))

    of = of.select("lang", *[discount(k).alias(f"d{k}") for k in (1, 2, 3)])
    g = grams.join(F.broadcast(of), "lang")  # a row for each language
    d = F.when(F.col("n") == 1, F.col("d1")).when(F.col("n") == 2, F.col("d2")).otherwise(F.col("d3"))
    g = g.withColumn("d", d)
    # whole numbers are summed up, so that the order of rows can't change a bit of the result
    times = [F.count_if(F.col("n") == 1).alias("c1"), F.count_if(F.col("n") == 2).alias("c2"), F.count_if(F.col("n") > 2).alias("c3")]
    contexts = g.groupBy("lang", "context").agg(F.sum("n").alias("total"), *times)
    g = g.join(contexts, ["lang", "context"]).withColumn("kept", F.col("c1") * F.col("d1") + F.col("c2") * F.col("d2") + F.col("c3") * F.col("d3"))
    weight = F.col("kept") / F.col("total")
    own = (F.col("n") - F.col("d")) / F.col("total")
    if lower is None:
        p = own + weight / F.lit(float(1 << BITS))
        return g.select("lang", "key", F.log2(p).cast("float").alias("p"), F.log2(weight).cast("float").alias("w"), "context")
    lower = lower.select("lang", F.col("key").alias("suffix"), F.col("p").alias("q"))
    g = g.join(lower, ["lang", "suffix"])
    return g.select("lang", "key", F.log2(own + weight * F.exp(F.col("q") * float(np.log(2)))).cast("float").alias("p"), F.log2(weight).cast("float").alias("w"), "context")


class Model:
    """Folder of the stored arrays; load() gives those of one language to a worker."""

    def __init__(self, folder: str, langs: list[str]):
        self.folder, self.langs = folder, langs

    def load(self, name: str) -> list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """By order: keys and log2 p, contexts and log2 weight, sorted."""
        import pyarrow.dataset as ds

        fs, path = file_system(self.folder)
        names = [f.path for f in fs.get_file_info(_selector(path)) if f.path.endswith(".parquet")]
        stored, levels = ds.dataset(names, filesystem=fs, format="parquet"), []
        for o in range(1, ORDER + 1):
            table = stored.to_table(columns=["key", "p", "w"], filter=(ds.field("lang") == name) & (ds.field("ord") == o))
            k, p, w = (table[c].to_numpy() for c in ("key", "p", "w"))
            at = np.argsort(k)
            k = k[at]
            c, first = np.unique(k >> BITS, return_index=True)
            levels.append((k, p[at].astype(np.float32), c, w[at][first].astype(np.float32)))
        return levels


def _selector(path: str):
    from pyarrow import fs

    return fs.FileSelector(path, recursive=True)


def fit(docs: DataFrame, scratch: Scratch, lang: str = "lang", text: str = "text") -> Model:
    """Count the whole corpus and store the model under the scratch folder."""
    prepare(docs.sparkSession)
    grams = [scratch.keep(count_ngrams(docs, lang, text))]
    for order in range(ORDER - 1, 0, -1):
        low = F.col("key").bitwiseAND(F.lit((1 << (BITS * order)) - 1))
        grams.append(grams[-1].groupBy("lang", low.alias("key")).agg(F.count(F.lit(1)).alias("n")))
    level, stored = None, []
    for order, g in enumerate(reversed(grams), 1):
        level = scratch.keep(_level(g, order, level).withColumn("ord", F.lit(order)))
        stored.append(level)
    model = stored[0]
    for x in stored[1:]:
        model = model.unionByName(x)
    model = scratch.keep(model.select("lang", "ord", "key", "p", "w").repartition(4, "lang", "ord"))
    langs = sorted(r["lang"] for r in model.select("lang").distinct().collect())  # a row for each language
    scratch.drop(grams[0], *stored)
    return Model(model._sheetgraph_path, langs)


def log2_probabilities(levels: list, words: list[str]) -> np.ndarray:
    """Sum of log2 p over the characters and the end of each word."""
    keys, owner = symbols_of(words)
    total = np.zeros(len(keys))
    open_ = np.arange(len(keys))
    for order in range(ORDER, 0, -1):
        grams, p, contexts, w = levels[order - 1]
        key = keys[open_] & ((1 << (BITS * order)) - 1)
        at = np.minimum(np.searchsorted(grams, key), max(0, len(grams) - 1))
        hit = grams[at] == key if len(grams) else np.zeros(len(key), bool)
        total[open_[hit]] += p[at[hit]]
        open_, key = open_[~hit], key[~hit]
        if not len(open_):
            break
        context = key >> BITS
        at = np.minimum(np.searchsorted(contexts, context), max(0, len(contexts) - 1))
        known = contexts[at] == context if len(contexts) else np.zeros(len(context), bool)
        total[open_[known]] += w[at[known]]
        if order == 1:
            total[open_] -= BITS
    return np.bincount(owner, weights=total, minlength=len(words))


def repeat_words(words: list[bytes], width: int = 5) -> int:
    """Words inside windows of five that occur twice or more in the text, the first one included."""
    if len(words) <= width:
        return 0
    windows = list(zip(*(words[k:] for k in range(width))))
    if len(set(windows)) == len(windows):
        return 0
    times = Counter(windows)
    marks, count = 0, 0
    for k, w in enumerate(windows):
        if times[w] > 1:
            count += k + width - max(k, marks)
            marks = k + width
    return count


def features_of(text: str, words: list[bytes]) -> tuple[int, int, int, int, int]:
    n_symbols = sum(map(text.count, SYMBOLS))
    lines = [x for x in text.split("\n") if x.strip(SPACES)]
    return len(words), len(text) - sum(map(text.count, SPACES)), n_symbols, len(lines) - len(set(lines)), repeat_words(words)


_loaded: dict[str, dict] = {}


def score(docs: DataFrame, model: Model, lang: str = "lang", text: str = "text", prefix: str = "") -> DataFrame:
    """All columns of docs, then the base features, base_failed and log2 perplexity a word."""
    prepare(docs.sparkSession)
    docs = without(docs, *(prefix + n for n, _ in FEATURES), prefix + "base_failed", prefix + "log_ppl")
    columns = docs.columns
    text_at, lang_at = columns.index(text), columns.index(lang)
    added = [(prefix + n, t) for n, t in FEATURES] + [(prefix + "base_failed", "boolean"), (prefix + "log_ppl", "double")]

    def make():
        if model.folder not in _loaded:
            _loaded.clear()
            _loaded[model.folder] = {}
        levels, counted = _loaded[model.folder], set(model.langs)
        caches: dict[str, dict[bytes, float]] = {}

        def log_ppl(some: list[tuple[str, list[bytes]]]) -> list[float | None]:
            new: dict[str, set] = {}
            for l, words in some:
                new.setdefault(l, set()).update(words)
            if sum(map(len, caches.values())) > CACHE_ENTRIES:
                caches.clear()
            for l, words in new.items():
                if l not in counted:
                    continue
                if l not in levels:
                    levels[l] = model.load(l)
                cache = caches.setdefault(l, {})
                fresh = [w for w in words if w not in cache]
                for k in range(0, len(fresh), PIECE):
                    part = fresh[k : k + PIECE]
                    got = log2_probabilities(levels[l], [w.decode("utf-8", "surrogatepass") for w in part])
                    cache.update(zip(part, got.tolist()))
            out = []
            for l, words in some:
                out.append(-sum(map(caches[l].__getitem__, words)) / len(words) if words and l in counted else None)
            return out

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            langs = [x or "und" for x in batch.column(lang_at).to_pylist()]
            rows, ppl, at = [], [], 0
            for some in runs_of(texts_of(batch.column(text_at))):
                lists = [words_of(t) for t in some]
                mine = [features_of(t, w) for t, w in zip(some, lists)]
                ppl += log_ppl(list(zip(langs[at : at + len(some)], lists)))
                at += len(some)
                rows += mine
            cols = [pa.array(c, pa.int64()) for c in zip(*rows)]
            failed = pa.array([r[0] < 10 or 100 * r[4] > 20 * r[0] for r in rows], pa.bool_())
            return pa.RecordBatch.from_arrays([*batch.columns, *cols, failed, pa.array(ppl, pa.float64())], names=[*columns, *(n for n, _ in added)])

        return step

    schema = T.StructType([*docs.schema.fields, *T._parse_datatype_string(", ".join(f"`{n}` {t}" for n, t in added)).fields])
    return map_arrow(docs, make, schema)


def verdicts(scored: DataFrame, lang: str = "lang", prefix: str = "", width: float = BAND_WIDTH) -> DataFrame:
    """scored with `kept`: inside its language's band and not failed by the base rule."""
    scored = without(scored, prefix + "kept")
    ppl, name = F.col(prefix + "log_ppl"), _language(lang)
    bands = quartiles(scored.where(ppl.isNotNull()).select(name.alias("lang"), ppl.alias("x")))
    of, low, high = unused(scored.columns, "__of", "__low", "__high")
    out = scored.join(F.broadcast(bands.toDF(of, low, high)), name == F.col(of), "left")  # a row for each language
    lo, hi = F.col(low), F.col(high)
    reach = F.lit(width) * F.greatest(hi - lo, F.lit(LEAST_RANGE)) * (1 + F.sqrt(F.lit(SHORT_WORDS) / F.greatest(F.col(prefix + "n_words"), F.lit(1))))
    inside = F.coalesce(ppl.between(lo - reach, hi + reach), F.lit(True))
    return out.withColumn(prefix + "kept", ~F.col(prefix + "base_failed") & inside).drop(of, low, high)


def quartiles(values: DataFrame) -> DataFrame:
    """lang, lower and upper quartile of x, from counts in bins of 1 / BINS: no partitioning changes them."""
    bins = values.groupBy("lang", F.floor(F.col("x") * BINS).alias("bin")).agg(F.count(F.lit(1)).alias("n"))
    w = Window.partitionBy("lang").orderBy("bin")  # rows are bins of a perplexity, some thousands
    bins = bins.withColumn("to", F.sum("n").over(w)).withColumn("all", F.sum("n").over(Window.partitionBy("lang")))

    def at(share: float) -> F.Column:
        return (F.min(F.when(F.col("to") > F.floor((F.col("all") - 1) * share), F.col("bin"))) + 0.5) / BINS

    return bins.groupBy("lang").agg(at(0.25).alias("low"), at(0.75).alias("high"))
