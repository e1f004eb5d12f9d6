"""Generation patterns of messy sheets: deterministic rewrites of clean cells, beside the clean truth.

A cell is rewritten where (row number * 7919 + salt) % 100 is under the pattern's share, so any engine can
rebuild it. Rewrites keep the row's and column's names, so statements can be told by cell.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace
from functools import partial, reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from sheetgraph.functions import text as X
from sheetgraph.operators import cells as C

SHARE = 30
#: Sheets of the four source graphs.
GRAPHS = {"K1": ("part", "supplier", "nation"), "K2": ("customer", "orders", "region"), "K3": ("events", "labels"), "K4": ("documents", "conversations")}


def _key() -> Column:
    """Row number: the first number in the row's name."""
    return F.regexp_extract("row_id", "^([0-9]+)", 1).cast("long")


def messed(salt: int, share: int = SHARE) -> Column:
    return F.pmod(_key() * 7919 + salt, F.lit(100)) < share


def _is(sheet: str, *cols: str) -> Column:
    return (F.col("sheet_id") == sheet) & F.col("col").isin(*cols)


def _text(cells: DataFrame, where: Column, new: Column, rich: bool = False) -> DataFrame:
    """The cells with new text where `where` holds; a number or date becomes text."""
    where = F.coalesce(where & new.isNotNull(), F.lit(False))
    none = {c: F.when(~where, F.col(c)) for c in ("n", "b", "format_class")}
    return cells.select(
        *("sheet_id", "row_id", "col", "style_key"),
        F.when(where, "S").otherwise(F.col("kind")).alias("kind"),
        F.when(where, new).otherwise(F.col("s")).alias("s"),
        none["n"].alias("n"),
        none["b"].alias("b"),
        none["format_class"].alias("format_class"),
        (F.when(where, new) if rich else F.lit(None).cast("string")).alias("new_rich"),
        "rich",
    ).withColumn("rich", F.coalesce("new_rich", "rich")).drop("new_rich").select(*C.CELL_COLUMNS)


@dataclass(frozen=True, eq=False)
class Cell:
    """A cell as column expressions of its table's row: one of s, n and b has a value, or it is blank."""

    sheet: str
    col: str
    s: Column | None = None
    n: Column | None = None
    b: Column | None = None
    fmt: str | None = None
    rich: Column | None = None
    there: Column | None = None  # whether n has a value, where the table tells it without making n
    whole: bool = False  # whether n is a whole number in every row


@dataclass(frozen=True)
class Rule:
    """A rewriting of cells. on: columns of sheets, or of any sheet; numbers: plain ones or dates; chance: which rows."""

    new: Callable[[Column, Column, Column, Column, Column], Column]  # of s, n, b, format class and column's name
    on: dict[str, tuple[str, ...]] | tuple[str, ...] | None = None
    numbers: str | None = None
    chance: Callable[[], Column] | None = None
    rich: bool = False
    alone: bool = False  # whether the new text is of the cell alone, not of its row

    def where(self) -> Column:
        """The condition over cells as rows."""
        out = F.lit(True)
        if isinstance(self.on, dict):
            out = reduce(Column.__or__, [_is(sheet, *cols) for sheet, cols in self.on.items()])
        elif self.on:
            out = F.col("col").isin(*self.on)
        if self.numbers:
            out = out & (F.col("format_class") == "date" if self.numbers == "date" else F.col("format_class").isNull() & (F.col("kind") == "N"))
        return out & self.chance() if self.chance else out

    def meets(self, c: Cell) -> bool:
        """Whether any row's cell of a column can meet it."""
        named = self.on is None or c.col in (self.on.get(c.sheet, ()) if isinstance(self.on, dict) else self.on)
        return named and (not self.numbers or c.n is not None and c.fmt == ("date" if self.numbers == "date" else None))

    def rewritten(self, c: Cell) -> Cell:
        """The same as `_text` over a cell as expressions."""
        s, n, b = (F.lit(None).cast(t) if x is None else x for x, t in ((c.s, "string"), (c.n, "double"), (c.b, "boolean")))
        there = s.isNotNull() | n.isNotNull() | b.isNotNull()
        new = self.new(s, n, b, F.when(n.isNotNull(), F.lit(c.fmt)), F.lit(c.col))
        where = F.coalesce(there & new.isNotNull() & (self.chance() if self.chance else F.lit(True)), F.lit(False))
        rest = {k: None if x is None else F.when(~where, x) for k, x in (("n", c.n), ("b", c.b))}
        rich = F.coalesce(F.when(where, new), c.rich if c.rich is not None else F.lit(None).cast("string")) if self.rich else c.rich
        return replace(c, s=F.when(where, new).otherwise(s), rich=rich, there=None, whole=False, **rest)


def _third() -> Column:
    return F.pmod(_key(), F.lit(3))


def _surface(s, n, b, f, col):
    return F.when(_third() == 0, F.upper(s)).when(_third() == 1, F.lower(s)).otherwise(F.replace(s, F.lit("#"), F.lit(" ")))


def _surface_date(s, n, b, f, col):
    day = F.date_add(F.lit("1899-12-30").cast("date"), F.floor(n).cast("int"))
    return F.when(_third() == 0, F.date_format(day, "yyyy-MM-dd")).when(_third() == 1, F.date_format(day, "M/d/yyyy")).otherwise(F.date_format(day, "d.M.yyyy"))


def _colored(s, n, b, f, col):
    color = F.when(_third() == 0, "#ff0000").when(_third() == 1, "#00ff00").otherwise("#0000ff")
    return F.concat(F.lit('<font color="'), color, F.lit('">'), F.coalesce(s, F.when(f == "date", X.serial_date(n))), F.lit("</font>"))


def _numbered(before: str, of: int, after: str) -> Column:
    return F.concat(F.lit(before), F.pmod(_key(), F.lit(of)).cast("string"), F.lit(after))


_OTHER = {"c_name": "c_mktsegment", "p_name": "p_brand", "lang": "source", "role": "text"}

RULES: dict[str, tuple[Rule, ...]] = {
    "clean": (),
    # acronyms or symbols: first letters for names, a mark or nothing for booleans
    "symbols": (
        Rule(lambda s, n, b, f, c: F.upper(F.substring(s, 1, 1)), {"customer": ("c_mktsegment",), "part": ("p_type",), "documents": ("lang",), "conversations": ("role",)}),
        Rule(lambda s, n, b, f, c: F.substring(s, 1, 1), {"orders": ("o_orderpriority",)}, chance=lambda: messed(1)),
        Rule(lambda s, n, b, f, c: F.when(b, F.lit("x")), {"labels": ("quality",)}),
    ),
    # intra-cell additional information: a remark in brackets behind the value
    "extra_information": (Rule(lambda s, n, b, f, c: F.concat(s, _numbered(" (", 50, ")")), {"part": ("p_name", "p_type"), "customer": ("c_name", "c_mktsegment"), "documents": ("lang", "source"), "events": ("event_type",)}, chance=lambda: messed(2)),),
    # multiple surface forms: spellings of names, and dates in English and German forms
    "surface_forms": (
        Rule(_surface, {"part": ("p_brand", "p_type"), "customer": ("c_mktsegment",), "conversations": ("role",), "documents": ("source",)}, chance=lambda: messed(3)),
        Rule(_surface_date, numbers="date", chance=lambda: messed(4)),
    ),
    # multiple types in a table: every third row of a sheet shows its names as another type; both cells keep their place
    "mixed_types": (Rule(lambda s, n, b, f, c: F.concat(F.lit("type "), F.coalesce(F.element_at(F.create_map(*[F.lit(x) for kv in _OTHER.items() for x in kv]), c), c)), (*_OTHER, *_OTHER.values()), chance=lambda: _third() == 0),),
    # numeric information as text: decimals with a comma or a point, whole numbers and dates spelled
    "numbers_as_text": (
        Rule(lambda s, n, b, f, c: F.replace(X.decimal_text(n), F.lit("."), F.lit(",")), ("o_totalprice", "c_acctbal", "value"), "plain", alone=True),
        Rule(lambda s, n, b, f, c: X.decimal_text(n), ("p_retailprice", "p_size", "s_acctbal", "n_chars", "turn"), "plain", alone=True),
        Rule(lambda s, n, b, f, c: X.serial_date(n), numbers="date", chance=lambda: messed(5, 50)),
    ),
    # outdated is formatted: an old value crossed out before the new one
    "outdated_struck": (Rule(lambda s, n, b, f, c: F.concat(_numbered("<strike>old ", 7, "</strike> "), s), {"customer": ("c_mktsegment",), "part": ("p_type",), "documents": ("source",), "conversations": ("role",), "events": ("event_type",)}, chance=lambda: messed(6), rich=True),),
    # partial formatting indicates relations: the value bold, a related one in italics beside it
    "relations_by_style": (Rule(lambda s, n, b, f, c: F.concat(F.lit("<b>"), s, F.lit("</b>, "), _numbered("<i>partner ", 9, "</i>")), {"part": ("p_brand",), "orders": ("o_orderpriority",), "events": ("event_type",), "documents": ("lang",)}, rich=True),),
    # property value as colour: the cell's value stays, in one of three colours by the row
    "value_as_color": (Rule(_colored, {"orders": ("o_orderdate",), "part": ("p_type",), "conversations": ("role",), "events": ("event_type",)}, rich=True),),
}
#: Patterns of which each cell of `all` gets one, in the order of their numbers.
STEPS = ("symbols", "surface_forms", "numbers_as_text", "extra_information", "outdated_struck", "relations_by_style", "value_as_color")


def _which() -> Column:
    return F.pmod(F.crc32(F.concat_ws("|", "col", "row_id")), F.lit(len(STEPS)))


def _rows(name: str, cells: DataFrame) -> DataFrame:
    """A pattern over cells as rows."""
    for r in RULES[name]:
        cells = _text(cells, r.where(), r.new(*[F.col(c) for c in ("s", "n", "b", "format_class", "col")]), r.rich)
    return cells.where(~(_is("labels", "quality") & F.coalesce(~F.col("b"), F.lit(False)))) if name == "symbols" else cells


def everything(cells: DataFrame) -> DataFrame:
    """All patterns in one sheet: each cell falls to one of them by its names."""
    return reduce(DataFrame.unionByName, [PATTERNS[step](cells.where(_which() == k)) for k, step in enumerate(STEPS)])


def in_row(name: str, c: Cell) -> Cell:
    """A pattern over a cell as expressions of its row, which has a row_id; the same object where it leaves the column alone."""
    if name == "all":
        which = F.pmod(F.crc32(F.concat_ws("|", F.lit(c.col), "row_id")), F.lit(len(STEPS)))
        got = {k: x for k, step in enumerate(STEPS) for x in [in_row(step, c)] if x is not c}
        if not got:
            return c
        out = {}
        for field in ("s", "n", "b", "rich"):
            plain = getattr(c, field)
            if plain is None and all(getattr(x, field) is None for x in got.values()):
                continue
            value = F.lit(None) if plain is None else plain
            for k, x in got.items():
                if getattr(x, field) is not plain:
                    value = F.when(which == k, F.lit(None) if getattr(x, field) is None else getattr(x, field)).otherwise(value)
            out[field] = value
        return replace(c, there=None, whole=False, **out)
    for r in RULES[name]:
        c = r.rewritten(c) if r.meets(c) else c
    if name == "symbols" and (c.sheet, c.col) == ("labels", "quality") and c.b is not None:
        c = replace(c, b=F.when(c.b, c.b))
    return c


def by_number(name: str, c: Cell) -> bool:
    """Whether a pattern makes a text of a column's number alone, so that equal numbers need it once."""
    rules = [r for r in RULES.get(name, ()) if r.meets(c)]
    return c.n is not None and c.s is None and c.b is None and bool(rules) and all(r.alone and r.chance is None for r in rules)


PATTERNS: dict[str, Callable[[DataFrame], DataFrame]] = {name: partial(_rows, name) for name in RULES} | {"all": everything}


def manual_sheet(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One sheet of twenty rows: whole numbers, a yes/no format, mixed dates, names to link, styled dates."""
    o = spark.read.parquet(f"{sf_dir}/orders.parquet").where("o_orderkey <= 20")
    c = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").alias("o_custkey"), "c_mktsegment")
    o = o.join(c, "o_custkey").withColumn("serial", F.floor(X.serial_of(F.col("o_orderdate"))).cast("double"))
    iso = X.serial_date(F.col("serial"))
    even = F.col("o_orderkey") % 2 == 0
    dates = F.concat(F.lit('<font color="#ff0000">'), X.serial_date(F.col("serial") + 30), F.lit("</font> <i>"), iso, F.lit("</i>"))

    def cell(name, s=None, n=None, b=None, fmt=None, rich=None):
        void = F.lit(None)
        return F.struct(F.lit(name).alias("col"), (void if s is None else s).cast("string").alias("s"), (void if n is None else n).cast("double").alias("n"), (void if b is None else b).cast("boolean").alias("b"), (void if fmt is None else fmt).cast("string").alias("format_class"), (void if rich is None else rich).cast("string").alias("rich"))

    row = F.array(
        cell("A", n=F.col("o_orderkey")),
        cell("B", b=F.col("o_orderstatus") == "F"),
        cell("C", s=F.when(even, iso), n=F.when(~even, F.col("serial")), fmt=F.when(~even, F.lit("date"))),
        cell("D", s=F.concat_ws("; ", "c_mktsegment", F.substring("o_orderpriority", 3, 20))),
        cell("E", s=dates, rich=dates),
    )
    out = o.select(F.col("o_orderkey").cast("string").alias("row_id"), F.inline(row))
    kind = F.when(F.col("b").isNotNull(), "B").when(F.col("n").isNotNull(), "N").otherwise("S")
    return out.withColumn("kind", kind).withColumn("sheet_id", F.lit("manual")).withColumn("style_key", F.lit(None).cast("string")).select(*C.CELL_COLUMNS)
