"""Other files as sheets: CSV, JSON lines, XML and text, with every value read as it stands there."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def csv(spark: SparkSession, path: str, columns: list[str], corrupt: str = "_corrupt") -> DataFrame:
    """All columns as text: inference would settle a mixed column's type; lines that do not fit stay in `corrupt`."""
    schema = ", ".join(f"`{c}` string" for c in [*columns, corrupt])
    return spark.read.schema(schema).option("header", True).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", corrupt).csv(path)


def json_lines(spark: SparkSession, path: str, schema: str, corrupt: str = "_corrupt") -> DataFrame:
    return spark.read.schema(f"{schema}, `{corrupt}` string").option("columnNameOfCorruptRecord", corrupt).json(path)


def xml(spark: SparkSession, path: str, row_tag: str, schema: str) -> DataFrame:
    return spark.read.schema(schema).option("rowTag", row_tag).xml(path)


def text(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.text(path)
