"""Expected mappings of the stand-in sheets, by hand, and the statements they give."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sheetgraph.operators import execute

# The template of each column, sheet by sheet
EXPECTED = {
    "region": {"r_regionkey": "T13", "r_name": "T9"},
    "nation": {"n_nationkey": "T13", "n_name": "T9", "n_regionkey": "T13"},
    "customer": {"c_custkey": "T13", "c_name": "T9", "c_nationkey": "T13", "c_acctbal": "N", "c_mktsegment": "T10"},
    "supplier": {"s_suppkey": "T13", "s_name": "T9", "s_nationkey": "T13", "s_acctbal": "N"},
    "part": {"p_partkey": "T13", "p_name": "T9", "p_brand": "T10", "p_type": "T10", "p_size": "T13", "p_retailprice": "N"},
    "orders": {"o_orderkey": "T13", "o_custkey": "T13", "o_orderstatus": "T10", "o_totalprice": "N", "o_orderdate": "T15", "o_orderpriority": "T10"},
    "lineitem": {"l_orderkey": "T13", "l_partkey": "T13", "l_suppkey": "T13", "l_linenumber": "T13", "l_quantity": "T13", "l_extendedprice": "N", "l_discount": "N", "l_tax": "N", "l_returnflag": "T10", "l_linestatus": "T10", "l_shipdate": "T15"},
    "events": {"event_id": "T13", "ts": "T15t", "user_id": "T13", "event_type": "T10", "value": "N", "props": "T9"},
    "documents": {"doc_id": "T13", "text": "T9", "lang": "T10", "source": "T10", "n_chars": "T13"},
    "pages": {"page_id": "T13", "url": "T9", "html": "T9"},
    "labels": {"doc_id": "T13", "quality": "T12", "toxic": "T12"},
    "conversations": {"conv_id": "T13", "turn": "T13", "role": "T10", "text": "T9"},
}
# end of fixed values
BASE = "urn:expected:"


def expected_mapping(spark: SparkSession, sheets: tuple[str, ...] = tuple(EXPECTED)) -> DataFrame:
    """N stands for any number as decimal, whole ones too."""
    rows = [(s, c, "T14" if t == "N" else t) for s in sheets for c, t in EXPECTED[s].items()]
    return execute.fixed(spark, rows)


def expected(spark: SparkSession, clean: DataFrame, sheets: tuple[str, ...] = tuple(EXPECTED)) -> DataFrame:
    """Statements of the clean cells under the expected mapping, with names of their own."""
    got = execute.run(expected_mapping(spark, sheets), clean, "calibrated", BASE)
    entity = F.replace("o", F.lit("urn:sheetgraph:entity/"), F.lit("urn:expected:entity/"))
    return got.withColumn("o", F.when(F.col("o_kind") == "iri", entity).otherwise(F.col("o")))
