"""Baselines: a flat extraction of CSV renderings, and ablations of the method."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sheetgraph.functions import text as X
from sheetgraph.operators import execute, tree


def render(cells: DataFrame, how: str = "display") -> DataFrame:
    """Cells as a CSV converter leaves them: text only. display: as shown; raw: as stored."""
    n, b, f = F.col("n"), F.col("b"), F.col("format_class")
    shown = F.when(f == "date", X.serial_date(n)).when(f == "datetime", X.serial_datetime(n)).otherwise(X.decimal_text(n))
    if how == "raw":
        shown = X.decimal_text(n)
    flag = F.when(b, "Yes").otherwise("No") if how == "display" else b.cast("int").cast("string")
    plain = F.regexp_replace(F.col("s"), "<[^>]*>", "")
    return cells.select("sheet_id", "row_id", "col", F.coalesce(plain, F.when(b.isNotNull(), flag), shown).alias("value"))


def extract(cells: DataFrame, how: str = "display", meta: bool = True) -> DataFrame:
    """Statements of the flat extractor: a literal for each cell, typed by its look, and bookkeeping ones."""
    v, base = F.col("value"), "urn:csv:"
    s = F.concat(F.lit(base), "sheet_id", F.lit("/"), "row_id")
    p = F.concat(F.lit(base), "sheet_id", F.lit("#"), F.initcap("col"))
    iri = v.rlike("^https?://")
    datatype = F.when(v.rlike(X.INT), "xsd:integer").when(v.rlike(X.DECIMAL_POINT), "xsd:float").otherwise("xsd:string")
    rows = render(cells, how).where(v.isNotNull() & (v != ""))
    main = rows.select("sheet_id", "row_id", "col", s.alias("s"), p.alias("p"), v.alias("o"), F.when(iri, "iri").otherwise("literal").alias("o_kind"), F.when(~iri, datatype).alias("o_datatype"))
    if not meta:
        return main
    column = rows.select("sheet_id", "row_id", "col", s.alias("s"), F.lit("urn:csv:vocab#column").alias("p"), F.col("col").alias("o"), F.lit("literal").alias("o_kind"), F.lit("xsd:string").alias("o_datatype"))
    return main.unionByName(column)


#: What `tree.build` gets where a part of the method is left out.
ABLATIONS = {
    "all_strings": {"templates": ("T9",)},
    "native_only": {"templates": ("T9", "T12", "T13", "T14", "T15", "T15t")},
    "no_recursion": {"max_depth": 1},
}


def ablation(cells: DataFrame, name: str, mode: str = "literal") -> DataFrame:
    """Statements of the method with a part of it left out."""
    return execute.run(execute.generate(tree.build(cells, mode, **ABLATIONS[name])), cells, mode)
