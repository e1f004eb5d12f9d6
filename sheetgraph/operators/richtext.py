"""Styled cell text: runs of equal style, extraction by style, and virtual columns.

A fold over the pieces between tags keeps what is open, so unclosed tags run to the end of the text.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sheetgraph.operators.cells import CELL_COLUMNS

TAGS = ("b", "i", "u", "strike")
STYLED = r"(?i)<(b|i|u|strike|font)[ >]"
RUNS = "array<struct<text:string,b:boolean,i:boolean,u:boolean,strike:boolean,color:string>>"
_STATE = f"struct<b:int,i:int,u:int,strike:int,colors:array<string>,runs:{RUNS}>"


def _unescape(t: Column) -> Column:
    for name, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&nbsp;", " "), ("&amp;", "&")):
        t = F.replace(t, F.lit(name), F.lit(char))
    return t


def runs(rich: Column) -> Column:
    """Runs of text with their styles, in order; black is no colour."""
    pieces = F.regexp_extract_all(rich, F.lit(r"(<[^>]*>|[^<]+|<)"), F.lit(1))
    start = F.struct(*[F.lit(0).alias(t) for t in TAGS], F.array().cast("array<string>").alias("colors"), F.array().cast(RUNS).alias("runs")).cast(_STATE)

    def step(state: Column, piece: Column) -> Column:
        tag = F.lower(F.regexp_extract(piece, r"^</?([A-Za-z]+)", 1))
        closing, is_tag = piece.startswith("</"), tag != ""
        color = F.lower(F.regexp_extract(piece, r"(?i)color *= *[\"']?(#[0-9a-f]{6})", 1))
        fields = []
        for t in TAGS:
            moved = F.when(closing, F.greatest(state[t] - 1, F.lit(0))).otherwise(state[t] + 1)
            fields.append(F.when(is_tag & (tag == t), moved).otherwise(state[t]).alias(t))
        popped = F.slice(state["colors"], F.lit(1), F.greatest(F.size(state["colors"]) - 1, F.lit(0)))
        fields.append(F.when(tag == "font", F.when(closing, popped).otherwise(F.concat(state["colors"], F.array(color)))).otherwise(state["colors"]).alias("colors"))
        last = F.try_element_at(state["colors"], F.lit(-1))
        shown = F.when(last.isNotNull() & ~last.isin("", "#000000"), last)
        run = F.struct(_unescape(piece).alias("text"), *[(state[t] > 0).alias(t) for t in TAGS], shown.alias("color"))
        fields.append(F.when(is_tag, state["runs"]).otherwise(F.concat(state["runs"], F.array(run))).alias("runs"))
        return F.struct(*fields).cast(_STATE)

    return F.aggregate(pieces, start, step, lambda s: s["runs"])


def style_of(run: Column) -> Column:
    """Name of a run's combination of styles; empty without any."""
    return F.concat_ws("+", *[F.when(run[t], F.lit(t)) for t in TAGS], run["color"])


def _joined(found: Column) -> Column:
    text = F.regexp_replace(F.trim(F.array_join(F.transform(found, lambda r: r["text"]), " ")), r"\s+", " ")
    return F.nullif(text, F.lit(""))


def styled_by_tag(rich: Column, tag: str) -> Column:
    return _joined(F.filter(runs(rich), lambda r: r[tag]))


def styled_by_color(rich: Column, color: str) -> Column:
    return _joined(F.filter(runs(rich), lambda r: r["color"] == color.lower()))


def unstyled(rich: Column) -> Column:
    return _joined(F.filter(runs(rich), lambda r: style_of(r) == ""))


def extractor(style_key: str) -> str:
    """Which function a style group is read with: emphasis first, then colour."""
    parts = style_key.split("+") if style_key else []
    tag = next((t for t in TAGS if t in parts), None)
    return f"tag:{tag}" if tag else f"color:{parts[0]}" if parts else "unformatted"


def split(cells: DataFrame) -> DataFrame:
    """Virtual columns for columns with styled cells; other columns stay as they are."""
    styled = cells.where(F.col("rich").rlike(STYLED)).select("sheet_id", "col").distinct().withColumn("styled", F.lit(True))
    marked = cells.join(F.broadcast(styled), ["sheet_id", "col"], "left")  # a row for each column
    plain = marked.where(F.col("styled").isNull()).select(*CELL_COLUMNS)
    rest = marked.where(F.col("styled"))
    text = rest.where(F.col("kind") == "S").withColumn("runs", runs(F.coalesce("rich", "s")))
    keys = F.array_distinct(F.transform("runs", style_of))
    each = text.select(*CELL_COLUMNS, "runs", F.explode(keys).alias("key"))
    virtual = each.withColumn("s", _joined(F.filter("runs", lambda r: style_of(r) == F.col("key")))).withColumn("style_key", F.col("key"))
    virtual = virtual.where(F.col("s").isNotNull()).withColumn("rich", F.lit(None).cast("string")).select(*CELL_COLUMNS)
    other = rest.where(F.col("kind") != "S").withColumn("style_key", F.lit("")).select(*CELL_COLUMNS)
    return plain.unionByName(virtual).unionByName(other)
