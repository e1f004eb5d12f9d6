"""A training corpus from the documents table: five stages, each on all rows its predecessor kept.

Language identification drops texts that no learned language explains better than the bare vocabulary does,
and writes the language it found into `lang`; quality rules drop documents that fail the base rule or leave
their language's perplexity band; near-duplicate classes keep one document each; mixing puts the rest in the
order of their sources' target weights; the last stage encodes whole texts to piece ids and gives each its
position in that order.

Defined results, for every stage: a null or empty text, or one without a letter, has no language and goes in
the first stage; in any other stage it is a row like others (the base rule drops it, it is its own class, it
has a place and no ids). A null doc_id or source is a value like others. Repeated rows are near-duplicates,
one stays. Ties: the smallest doc_id stays. Empty tables give empty tables. Extra columns pass through, also
those named like a stage's inner ones; the last stage returns its own columns only.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sheetgraph.llm import langid, lattice, order_minhash, perplexity, pfair
from sheetgraph.llm._shared import Scratch, documents, unused
from sheetgraph.llm.queries import MIX, tokenizer_file


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = langid.fit(docs, tokenizer_file("piece_bpe_32k.model"), ~langid.held_out())
    lang, score, margin = unused(docs.columns, "__lang", "__score", "__margin")
    told = langid.predict(docs, model, lang_col=lang, score_col=score, margin_col=margin).where((F.col(lang) != "und") & (F.col(margin) > 0))
    return told.select(*[F.col(lang).alias(c) if c == "lang" else F.col(f"`{c}`") for c in docs.columns])


def apply_quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, "quality")
    prefix = unused([c[:4] for c in docs.columns], "__q_")[0]
    scored = scratch.keep(perplexity.score(docs, perplexity.fit(docs, scratch), prefix=prefix))
    return perplexity.verdicts(scored, prefix=prefix).where(prefix + "kept").select(*[F.col(f"`{c}`") for c in docs.columns])


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return order_minhash.keep_first(docs, Scratch(spark, "dedup"))


def _placed(docs: DataFrame) -> tuple[DataFrame, str]:
    """docs in the order of their sources' target weights, and the name of the column with their positions."""
    prefix = unused([c[:4] for c in docs.columns], "__m_")[0]
    return pfair.in_order(pfair.schedule(docs, MIX, prefix=prefix), prefix=prefix), prefix + "position"


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return _placed(docs)[0].select(*[F.col(f"`{c}`") for c in docs.columns])


def encode_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, "encode")
    # files do not keep the order of rows; places follow from keys and sources alone, so the schedule gives them again
    placed, position = _placed(docs.select("doc_id", "text", "lang", "source"))
    placed = scratch.keep(placed.select("doc_id", "text", "lang", "source", F.col(position).alias("position")))
    encoded = lattice.encode(placed, tokenizer_file("piece_bpe_32k.model"), scratch, ids_col="ids", merged=True, keep_text=False)
    return encoded.select("doc_id", "lang", "source", "position", F.size("ids").alias("n_tokens"), "ids")


STAGES = [
    ("language_id", identify_language),
    ("quality_rules", apply_quality_rules),
    ("near_dedup", drop_near_duplicates),
    ("mix_sources", mix_sources),
    ("sentencepiece", encode_pieces),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in order; what each returns is written to the shared folder and read again."""
    scratch = Scratch(spark, "pipeline")
    docs = documents(spark, sf_dir)
    for k, (_, stage) in enumerate(STAGES, 1):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES):
            docs = scratch.keep(docs)
    return docs


#: Trained models and near-duplicate classes are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None
