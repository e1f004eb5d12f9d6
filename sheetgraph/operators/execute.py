"""Mappings: made from trees, printed, and run over cells to RDF statements with their provenance."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sheetgraph.functions import text as X
from sheetgraph.operators.heuristics import REGISTERED, all_templates
from sheetgraph.operators.profile import BITS, COLUMN, number_mask, text_mask

TRIPLES = ("sheet_id", "row_id", "col", "s", "p", "o", "o_kind", "o_datatype")


def generate(nodes: DataFrame) -> DataFrame:
    """One predicate-object map a (virtual) column: its templates in order, as an array of objects."""
    one = F.struct("level", "template", "score", "cells", "loose")
    return nodes.groupBy(*COLUMN).agg(F.sort_array(F.collect_list(one)).alias("objects"))


def fixed(spark, rows: list[tuple[str, str, str]]) -> DataFrame:
    """A mapping by hand: (sheet, column, template)."""
    made = spark.createDataFrame([(a, b, None, 0, t, 1.0, 0, 0, True) for a, b, t in rows], "sheet_id string, col string, style_key string, level int, template string, score double, rank int, cells long, loose boolean")
    return generate(made)


#: Templates that look into a text to tell whether they cover it.
TEXT_READING = ("T2", "T3", "T4", "T5", "T6", "T7", "T8")


def cover_cases(text: Column, number: Column, flag: Column, f: Column, bit: Callable[[str], Column], loose: Column, mode: str) -> dict[str, Callable[[], Column]]:
    """Whether each template can map a cell of a kind and format; bit: what its text or number looks like. Each is made when called."""

    def counted() -> Column:
        return number if mode == "literal" else number & (F.coalesce(f.isin("date", "datetime"), F.lit(False)) | loose)

    any_number = F.lit(mode == "calibrated")
    return {
        "T2": lambda: (text & bit("int")) | (number & bit("whole")),
        "T3": lambda: (text & bit("point")) | (number & bit("fraction")),
        "T4": lambda: (text & bit("comma")) | (number & bit("fraction")),
        "T5": lambda: (text & bit("date")) | counted(),
        "T6": lambda: (text & bit("datetime")) | counted(),
        "T7": lambda: text & bit("list"),
        "T8": lambda: text & (bit("word") | loose),
        "T9": lambda: F.lit(True),
        "T10": lambda: text,
        "T11": lambda: text,
        "T12": lambda: flag,
        "T13": lambda: number & (bit("whole") | any_number),
        "T14": lambda: number & (bit("fraction") | any_number),
        "T15": lambda: number & F.coalesce(f == "date", F.lit(False)),
        "T15t": lambda: number & F.coalesce(f == "datetime", F.lit(False)),
    }


def _covers(template: Column, loose: Column, mode: str) -> Column:
    """Whether an object's template can map the cell in the row; loose: what the tree decided by the column."""
    m, k, f = F.col("mask"), F.col("kind"), F.col("format_class")
    cases = cover_cases(k == "S", k == "N", k == "B", f, lambda name: m.bitwiseAND(F.lit(BITS[name])) != 0, loose, mode)
    cases |= {k: x.applies for k, x in REGISTERED.items()}
    out = None
    for t, test in cases.items():
        out = F.when(template == t, test()) if out is None else out.when(template == t, test())
    return F.coalesce(out, F.lit(False))


def object_cases(s: Column, n: Column, b: Column, loose: Column) -> dict[str, Callable[[], Column]]:
    """Lexical forms or IRIs of a cell under each template, as arrays; each is made when called."""

    def number() -> Column:
        return X.decimal_text(n)

    return {
        "T2": lambda: F.array(F.coalesce(X.parse_number(s, integer=True), number())),
        "T3": lambda: F.array(F.coalesce(X.parse_number(s, "."), number())),
        "T4": lambda: F.array(F.coalesce(X.parse_number(s, ","), number())),
        "T5": lambda: F.array(F.coalesce(X.date_text(s), X.find_date(s), X.serial_date(n), number())),  # a number off the calendar stays one
        "T6": lambda: F.array(F.coalesce(X.datetime_text(s), X.serial_datetime(n), number())),
        "T7": lambda: X.parse_numbers(s),
        "T8": lambda: F.array(F.coalesce(X.parse_boolean(s), F.when(loose, F.lit(True))).cast("string")),
        "T9": lambda: F.array(F.coalesce(s, F.when(b.isNotNull(), b.cast("string")), number())),
        "T10": lambda: F.array(X.entity_iri(s)),
        "T11": lambda: F.when(F.size(X.tokens(s)) > 0, F.array_distinct(F.transform(X.tokens(s), X.entity_iri))).otherwise(F.array(X.entity_iri(s))),
        "T12": lambda: F.array(b.cast("string")),
        "T13": lambda: F.array(number()),
        "T14": lambda: F.array(number()),
        "T15": lambda: F.array(F.coalesce(X.serial_date(n), number())),
        "T15t": lambda: F.array(F.coalesce(X.serial_datetime(n), number())),
    }


def _objects() -> Column:
    """Lexical forms or IRIs of a cell under its template."""
    t = F.col("template")
    cases = object_cases(F.col("s"), F.col("n"), F.col("b"), F.col("loose"))
    cases |= {k: x.objects for k, x in REGISTERED.items()}
    out = None
    for k, v in cases.items():
        out = F.when(t == k, v()) if out is None else out.when(t == k, v())
    return out


def run(mapping: DataFrame, cells: DataFrame, mode: str = "literal", base: str = "urn:sheetgraph:") -> DataFrame:
    """Statements of every cell under the first object of its column that can map it.

    The mapping has a row for each column and is joined by column; cells are not shuffled where Spark finds
    it small, and any number of sheets is a join on (sheet, column) else.
    """
    m = mapping.select(F.col("sheet_id").alias("m_sheet"), F.col("col").alias("m_col"), F.col("style_key").alias("m_style"), "objects")
    on = (F.col("sheet_id") == F.col("m_sheet")) & (F.col("col") == F.col("m_col")) & F.coalesce("style_key", F.lit("-")).eqNullSafe(F.coalesce("m_style", F.lit("-")))
    joined = cells.join(m, on)
    # texts are read only in columns with a template that asks for it
    reads = F.exists("objects", lambda o: o["template"].isin(*TEXT_READING, *REGISTERED))
    masked = joined.withColumn("mask", F.when((F.col("kind") == "S") & reads, text_mask(F.col("s"))).when(F.col("kind") == "N", number_mask(F.col("n"))).otherwise(0))
    # exploded, not filtered: a condition would go below the join and read every text once more
    found = F.slice(F.filter("objects", lambda o: _covers(o["template"], o["loose"], mode)), 1, 1)
    chosen = masked.select(*cells.columns, F.explode(found).alias("found")).select(*cells.columns, "found.template", "found.loose")
    each = chosen.select(*CELL_KEYS, "template", F.explode(_objects()).alias("o")).where(F.col("o").isNotNull())
    datatype = F.create_map(*[F.lit(x) for t in all_templates() for x in (t.id, t.datatype)])
    column = F.concat(F.lit(base), F.col("sheet_id"), F.lit("/prop/"), F.col("col"), F.when(F.coalesce("style_key", F.lit("")) != "", F.concat(F.lit("#"), F.replace("style_key", F.lit("#"), F.lit("%23")))).otherwise(""))
    return each.select(
        "sheet_id",
        "row_id",
        "col",
        F.concat(F.lit(base), F.col("sheet_id"), F.lit("/row/"), F.col("row_id")).alias("s"),
        column.alias("p"),
        "o",
        F.when(F.col("template").isin("T10", "T11"), "iri").otherwise("literal").alias("o_kind"),
        F.nullif(F.element_at(datatype, F.col("template")), F.lit("")).alias("o_datatype"),
    )


CELL_KEYS = ("sheet_id", "row_id", "col", "style_key")


def lexicon(mapping: DataFrame, cells: DataFrame, mode: str = "literal") -> DataFrame:
    """Entities that entity templates mention, with a label each."""
    t = run(mapping, cells, mode).where("o_kind = 'iri'")
    labels = cells.where("kind = 'S'").select(F.explode(F.concat(F.array("s"), X.tokens(F.col("s")))).alias("label")).distinct()
    labels = labels.select(X.entity_iri(F.col("label")).alias("o"), "label").groupBy("o").agg(F.min("label").alias("label"))
    return t.select("o").distinct().join(labels, "o").select(F.col("o").alias("entity"), "label")


def turtle_lines(mapping: DataFrame) -> DataFrame:
    """A predicate-object map in Turtle for each object of each column."""
    rows = mapping.select(*COLUMN, F.explode("objects").alias("obj"))
    t = F.col("obj.template")

    def of(field: str) -> Column:
        return F.element_at(F.create_map(*[F.lit(x) for k in all_templates() for x in (k.id, getattr(k, field))]), t)

    datatype = F.when(of("datatype") != "", F.concat(F.lit("; rr:datatype "), of("datatype"))).otherwise("")
    function = F.when(of("function") != "", F.concat(F.lit('; fn:call "'), of("function"), F.lit('"'))).otherwise("")
    term = F.when(of("term") == "iri", "rr:IRI").otherwise("rr:Literal")
    # a virtual column is read out of the styled text first, then by its template's own function
    key = F.coalesce("style_key", F.lit("-"))
    tag = F.regexp_extract(key, r"^(b|i|u|strike)\b", 1)
    styled = F.when(key == "-", "").when(key == "", '; fn:from "getEntitiesByUnformatted"').when(tag != "", F.concat(F.lit('; fn:from "getEntitiesByTag"; fn:tag "'), tag, F.lit('"'))).otherwise(F.concat(F.lit('; fn:from "getEntitiesByColor"; fn:color "'), key, F.lit('"')))
    function = F.concat(styled, function)
    style = F.when(key.isin("-", ""), "").otherwise(F.concat(F.lit("#"), F.replace(key, F.lit("#"), F.lit("%23"))))
    line = F.concat(F.lit("[] rr:predicate <urn:sheetgraph:"), "sheet_id", F.lit("/prop/"), "col", style, F.lit('>; rr:objectMap [ ml:reference "'), of("reference"), F.lit('"; rr:termType '), term, datatype, function, F.lit(" ] ."))
    return rows.select(*COLUMN, F.col("obj.level").alias("level"), line.alias("line"))


def ntriples(triples: DataFrame) -> DataFrame:
    """Statements as N-Triples lines."""
    escaped = F.regexp_replace(F.regexp_replace(F.regexp_replace(F.regexp_replace("o", r"\\", r"\\\\"), '"', r'\\"'), "\n", r"\\n"), "\r", r"\\r")
    kind = F.when(F.col("o_datatype").isNotNull(), F.concat(F.lit("^^<http://www.w3.org/2001/XMLSchema#"), F.replace("o_datatype", F.lit("xsd:"), F.lit("")), F.lit(">"))).otherwise("")
    o = F.when(F.col("o_kind") == "iri", F.concat(F.lit("<"), "o", F.lit(">"))).otherwise(F.concat(F.lit('"'), escaped, F.lit('"'), kind))
    return triples.select(F.concat(F.lit("<"), "s", F.lit("> <"), "p", F.lit("> "), o, F.lit(" .")).alias("line"))


