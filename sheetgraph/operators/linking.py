"""Entity linking: labels of a lexicon found in texts, by joins on word n-grams or by an automaton."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def _normal(c):
    return F.trim(F.regexp_replace(F.lower(c), r"[^\p{L}\p{N}]+", " "))


def link_ngrams(texts: DataFrame, lexicon: DataFrame, key: str, text: str, most: int | None = None) -> DataFrame:
    """key, label for every label that a text holds as whole words. Any lexicon size: an equi-join that Spark
    broadcasts where the lexicon is small. most: words of the longest label, counted where not given."""
    if most is None:
        most = lexicon.agg(F.max(F.size(F.split(_normal(F.col("label")), " ")))).first()[0] or 1
    words = F.split(_normal(F.col(text)), " ")
    grams = texts.select(key, F.explode(F.array_distinct(F.flatten(F.transform(F.sequence(F.lit(1), F.lit(most)), lambda n: F.transform(F.sequence(F.lit(1), F.greatest(F.size(words) - n + 1, F.lit(1))), lambda i: F.array_join(F.slice(words, i, n), " ")))))).alias("gram"))
    labels = lexicon.select("label", _normal(F.col("label")).alias("gram")).distinct()
    return grams.join(labels, "gram").select(key, "label").distinct()


def link_automaton(texts: DataFrame, lexicon: DataFrame, key: str, text: str, overlap: str = "longest", max_labels: int = 1_000_000) -> DataFrame:
    """key, label by one pass of a multi-pattern automaton over each text.

    The automaton is in every worker, so a lexicon beyond max_labels is refused: link_ngrams takes any.

    overlap: longest keeps the longest of overlapping labels, all every one.
    """
    rows = lexicon.select("label").distinct().limit(max_labels + 1).collect()
    if len(rows) > max_labels:
        raise ValueError(f"more than {max_labels} labels: use link_ngrams")
    labels = [r["label"] for r in rows]
    kind = texts.schema[key].dataType.simpleString()

    def run(batches):
        import ahocorasick

        auto = ahocorasick.Automaton()
        for x in labels:
            auto.add_word(f" {' '.join(x.lower().split())} ", x)
        auto.make_automaton()
        for batch in batches:
            keys, found = [], []
            for k, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                plain = "  ".join("".join(c if c.isalnum() else " " for c in (t or "").lower()).split())
                hay = " " + plain.replace("  ", " ") + " "
                spans = sorted(((end - len(x) - 1, end, x) for end, x in (auto.iter(hay) if labels else ())), key=lambda s: (s[0], -s[1]))
                last, seen = -1, set()
                for start, end, x in spans:
                    if (overlap == "all" or start >= last) and x not in seen:
                        seen.add(x)
                        keys.append(k)
                        found.append(x)
                        last = end - 1
            yield pa.RecordBatch.from_arrays([pa.array(keys, batch.schema.field(0).type), pa.array(found, pa.string())], names=[key, "label"])

    return texts.select(key, text).mapInArrow(run, f"`{key}` {kind}, label string")
