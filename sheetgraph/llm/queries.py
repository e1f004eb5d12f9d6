"""Queries of the operators of this subpackage over the given tables, with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from sheetgraph.llm import bpe_count, langid, lattice, licenses, mpeg, order_minhash, perplexity, pfair, rendezvous, sstable
from sheetgraph.llm._shared import Scratch, documents


def tokenizer_file(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_rendezvous_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rendezvous.assign(documents(spark, sf_dir), [1.0] * 24)


def op2_order_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return order_minhash.classes(documents(spark, sf_dir), Scratch(spark, "op2"))


def op3_sorted_string_tables(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, "op3")
    manifest = sstable.write_shards(documents(spark, sf_dir), tokenizer_file("word_bpe_49k.json"), scratch)
    return sstable.read_shards(manifest)


def op4_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    held = langid.held_out()
    model = langid.fit(docs, tokenizer_file("piece_bpe_32k.model"), ~held)
    return langid.predict(docs.select("doc_id", "text"), model).select("doc_id", held.alias("held_out"), "lang_pred", "score")


def op5_piece_lattice(spark: SparkSession, sf_dir: str) -> DataFrame:
    model = tokenizer_file("piece_bpe_32k.model")
    docs = documents(spark, sf_dir).select("doc_id", "text")
    return lattice.encode(docs, model, Scratch(spark, "op5"), finish=lattice.DIGEST, merged=True, keep_text=False)


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_count.count_tokens(documents(spark, sf_dir), tokenizer_file("piece_bpe_32k.model"))


def op7_ngram_perplexity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "lang", "text")
    scratch = Scratch(spark, "op7")
    scored = scratch.keep(perplexity.score(docs, perplexity.fit(docs, scratch)).drop("text"))
    names = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "log_ppl"]
    return perplexity.verdicts(scored).select(*names)


def op8_license_sentences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(documents(spark, sf_dir))


def op9_mpeg_audio(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mpeg.store_and_measure(documents(spark, sf_dir), Scratch(spark, "op9"))


#: Target weights of the given sources, in quanta.
MIX = {f"src{i}": 1 + i % 4 for i in range(20)}


def op10_pfair_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "source")
    return pfair.schedule(docs, MIX)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_rendezvous_shards": op1_rendezvous_shards,
    "op2_order_minhash": op2_order_minhash,
    "op3_sorted_string_tables": op3_sorted_string_tables,
    "op4_language_id": op4_language_id,
    "op5_piece_lattice": op5_piece_lattice,
    "op6_token_counts": op6_token_counts,
    "op7_ngram_perplexity": op7_ngram_perplexity,
    "op8_license_sentences": op8_license_sentences,
    "op9_mpeg_audio": op9_mpeg_audio,
    "op10_pfair_mix": op10_pfair_mix,
}

ORACLE_SQL: dict[str, str] = {}
