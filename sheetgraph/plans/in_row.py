"""Grading in the row: a cell's statements, actual and expected, are made and met where its table's row is read.

A cell's grade depends on the cell alone, so nothing but sums leaves a row: no statement is shuffled, stored
or sent to Python. Texts whose templates read them leave it once a different text, with their number. Cells go
once into the dictionary that trees are built from, which is stored, numbers as sums; the chosen mapping, a few rows a column, comes to the driver and becomes expressions over the table's columns, the same
ones that `execute.run` puts over cells. The expected side has one predicate a column, so the best match of a
cell is the best of its actual predicates, each against that one (`match.star`).

Statements of rows that share a row's name are one graph, so tables with repeated names, and registered
templates, which read cells as rows, go the general way: `possible` says which.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from functools import lru_cache, reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sheetgraph.functions import text as X
from sheetgraph.operators import cells as C
from sheetgraph.operators import execute, match, richtext, tree
from sheetgraph.operators.heuristics import REGISTERED, TEMPLATES
from sheetgraph.operators.profile import BITS, number_mask, text_tests, value_dictionary
from sheetgraph.plans import truth
from sheetgraph.plans.mess import Cell
from sheetgraph.plans.store import keep

IRI = ("T10", "T11")
LISTS = ("T7", "T11")  # templates of several objects a cell
Counts = tuple[Column, Column, Column]  # statements met, actual ones, expected ones


@dataclass(frozen=True)
class Sheet:
    """A table's rows as row_id and one column a cell, the cells as a method sees them, and the clean ones.

    names: the sheet of each cell's column in dictionary and trees; runs: those that count it, each with the sheet
    of the trees it takes. So a column that many runs see alike is there, and is counted, once.
    """

    name: str
    df: DataFrame
    seen: tuple[Cell, ...]
    clean: tuple[Cell, ...]
    names: tuple[str, ...] = ()
    runs: tuple[tuple[tuple[str, str], ...], ...] = ()

    def __post_init__(self):
        names = self.names or (self.name,) * len(self.seen)
        object.__setattr__(self, "names", names)
        object.__setattr__(self, "runs", self.runs or tuple(((n, n),) for n in names))

    def cells(self) -> list[tuple[Cell, Cell, str, tuple[tuple[str, str], ...]]]:
        return list(zip(self.seen, self.clean, self.names, self.runs))


def read(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, tuple[Cell, ...]]:
    """A table with its cells' values by name; line items need no ordinal, as nothing asks for their rows' names."""
    raw, spec = spark.read.parquet(f"{sf_dir}/{name}.parquet"), C.SPECS[name]
    columns, cells = [C.row_id(spec).alias("row_id")] if set(spec.key) <= set(raw.columns) else [], []
    for col in spec.columns or tuple(raw.columns):
        kind, fmt = raw.schema[col].dataType, spec.formats.get(col)
        of = "s" if isinstance(kind, T.StringType) else "b" if isinstance(kind, T.BooleanType) or fmt == "bool" else "n"
        if of == "n" and isinstance(kind, (T.TimestampType, T.TimestampNTZType, T.DateType)):
            fmt = fmt or ("date" if isinstance(kind, T.DateType) else "datetime")
        columns.append(C._cell(col, kind, spec)[of].alias(f"{name}__{col}"))
        there = None
        if of == "n":  # a date's number is dear, and most grades ask only whether there is one
            columns.append(F.col(f"`{col}`").isNotNull().alias(f"{name}__{col}__there"))
            there = F.col(f"{name}__{col}__there")
        cells.append(Cell(name, col, fmt=fmt if of == "n" and fmt in ("date", "datetime") else None, there=there, whole=of == "n" and isinstance(kind, T.IntegralType), **{of: F.col(f"{name}__{col}")}))
    return raw.select(*columns), tuple(cells)


def by_cell(df: DataFrame, name: str, col: str) -> DataFrame:
    """The different cells of one column of a table as `read`, w times each."""
    columns = [c for c in (f"{name}__{col}", f"{name}__{col}__there") if c in df.columns]
    return df.groupBy(*columns).agg(F.count(F.lit(1)).alias("w"))


def _times(df: DataFrame) -> Column:
    """How many of the table's rows a row stands for."""
    return F.col("w") if "w" in df.columns else F.lit(1).cast("long")


def possible(spark: SparkSession, sf_dir: str, names: tuple[str, ...]) -> bool:
    """Whether every row of the tables has a name of its own. A line item's ordinal gives it one, unless its key has nulls."""
    if REGISTERED:
        return False
    out = []
    for name in names:
        raw, spec = spark.read.parquet(f"{sf_dir}/{name}.parquet"), C.SPECS[name]
        if set(spec.key) <= set(raw.columns):
            # of one whole number, the number tells the same as its name
            plain = len(spec.key) == 1 and isinstance(raw.schema[spec.key[0]].dataType, T.IntegralType)
            out.append(raw.groupBy(spec.key[0] if plain else C.row_id(spec)).count().where("count > 1").select(F.lit(1).alias("x")))
        else:
            keys = [F.col(k) for k in spec.key if k in raw.columns]
            out.append(raw.where(reduce(Column.__or__, [k.isNull() for k in keys])).select(F.lit(1).alias("x")))
    return reduce(DataFrame.unionByName, out).limit(1).count() == 0


@lru_cache(maxsize=4096)  # a cell is itself only: building expressions is most of a small run's time
def _fields(c: Cell) -> tuple[Column, Column, Column, Column]:
    s, n, b = (F.lit(None).cast(t) if x is None else x for x, t in ((c.s, "string"), (c.n, "double"), (c.b, "boolean")))
    return s, n, b, F.when(_there(c), F.lit(c.fmt).cast("string"))


def _there(c: Cell) -> Column:
    """Whether the cell has a number."""
    return F.lit(False) if c.n is None else c.n.isNotNull() if c.there is None else c.there


# ---- styles


def _virtual(c: Cell) -> Column:
    """Texts of a styled cell by style, as `richtext.split` makes them."""

    def of(runs: Column) -> Column:
        keys = F.array_distinct(F.transform(runs, richtext.style_of))
        return F.transform(keys, lambda k: F.struct(k.alias("key"), richtext._joined(F.filter(runs, lambda r: richtext.style_of(r) == k)).alias("s")))

    rich = c.s if c.rich is None else F.when(c.s.isNotNull(), F.coalesce(c.rich, c.s))
    found = F.get(F.transform(F.array(richtext.runs(rich)), of), F.lit(0))
    return F.map_from_entries(F.filter(found, lambda x: x["s"].isNotNull()))


def _staged(sheet: Sheet, styled: set[tuple[str, str]]) -> Sheet:
    """The columns without styles, every rewritten field as a column."""
    columns, kept = [], []
    for k, (c, clean, name, runs) in enumerate(sheet.cells()):
        if (name, c.col) in styled:
            continue
        new = {}
        for field in ("s", "n", "b") if c is not clean else ():
            if getattr(c, field) is not None:
                columns.append(getattr(c, field).alias(f"x{k}{field}"))
                new[field] = F.col(f"x{k}{field}")
        kept.append((c if c is clean else Cell(c.sheet, c.col, fmt=c.fmt, **new), clean, name, runs))
    return Sheet(sheet.name, sheet.df.select("*", *columns) if columns else sheet.df, *(zip(*kept) if kept else ((), ())))


def _styled(sheet: Sheet, styled: set[tuple[str, str]]) -> list[Sheet]:
    """A sheet for each styled column: its different pairs of seen and clean cell, w times each, with `texts` by style.

    Reading the styles of a text is the dearest step, so it is done once a pair and not once a row.
    """
    out = []
    for c, clean, name, runs in sheet.cells():
        if (name, c.col) in styled:
            columns, cells = [], []
            for side, x in (("x", c), ("y", clean)):
                new = {f: getattr(x, f) for f in ("s", "n", "b", "rich") if getattr(x, f) is not None}
                columns += [v.alias(side + f) for f, v in new.items()]
                cells.append(Cell(x.sheet, x.col, fmt=x.fmt, **{f: F.col(side + f) for f in new}))
            pairs = sheet.df.select(*columns, _times(sheet.df).alias("w"))
            pairs = pairs.groupBy(*pairs.columns[:-1]).agg(F.sum("w").alias("w"))
            out.append(Sheet(sheet.name, pairs.select("*", _virtual(cells[0]).alias("texts")), (cells[0],), (cells[1],), (name,), (runs,)))
    return out


def styled_columns(sheets: list[Sheet]) -> set[tuple[str, str]]:
    """Columns with a styled cell: one look at those that a pattern can style."""
    out = []
    for x in sheets:
        for c, _, name, _ in x.cells():
            if c.rich is not None:
                out.append(x.df.where(c.rich.rlike(richtext.STYLED)).limit(1).select(F.lit(name).alias("sheet"), F.lit(c.col).alias("col")))
    return {tuple(r) for r in reduce(DataFrame.unionByName, out).collect()} if out else set()


# ---- trees


def _numbers(sheet: Sheet) -> DataFrame | None:
    """The dictionary's rows of the columns without texts: a count for each class, from sums over the table."""
    counts, rows = [], []

    def count(which: Column) -> Column:
        return F.coalesce(F.sum(F.when(which, F.col("w"))), F.lit(0)) if "w" in sheet.df.columns else F.count_if(which)

    for k, c in enumerate(sheet.seen):
        if c.s is not None:
            continue
        flag = F.lit(False) if c.b is None else c.b.isNotNull()
        counts.append(count(flag).alias(f"b{k}"))
        classes = [("B", None, 0, F.col(f"b{k}"))]
        if c.n is not None:
            number = _there(c) if c.b is None else ~flag & _there(c)
            counts.append(count(number).alias(f"n{k}"))
            if not c.whole:
                counts.append(count(number & (number_mask(c.n) == BITS["whole"])).alias(f"w{k}"))
            whole = F.col(f"n{k}" if c.whole else f"w{k}")
            classes += [("N", c.fmt, BITS["whole"], whole), ("N", c.fmt, BITS["fraction"], F.col(f"n{k}") - whole)]
        for kind, fmt, mask, cnt in classes:
            rows.append(F.struct(F.lit(sheet.names[k]).alias("sheet_id"), F.lit(c.col).alias("col"), F.lit(kind).alias("kind"), F.lit(fmt).cast("string").alias("format_class"), F.lit(None).cast("string").alias("value"), cnt.alias("cnt"), F.lit(mask).alias("mask")))
    if not counts:
        return None
    each = sheet.df.agg(*counts).select(F.lit(None).cast("string").alias("style_key"), F.inline(F.array(*rows)))
    return each.where("cnt > 0")


def dictionary(sheets: list[Sheet], styled: set[tuple[str, str]]) -> DataFrame:
    """The stored dictionary of all cells' values; only columns with texts make a row for each cell."""
    out, numbers = [], []
    one = "array<struct<sheet_id:string,col:string,style_key:string,s:string,n:double,b:boolean,format_class:string>>"
    void = F.lit(None).cast("string")
    for sheet in sheets:
        parts = []
        staged = _staged(sheet, styled)
        numbers.append(_numbers(staged))
        texts = [(name, c) for c, _, name, _ in staged.cells() if c.s is not None]
        if texts:
            rows = F.array(*[F.struct(F.lit(name), F.lit(c.col), void, *_fields(c)).cast(one[6:-1]) for name, c in texts])
            parts.append(staged.df.select(F.inline(rows), _times(staged.df).alias("w")))
        for x in _styled(sheet, styled):
            c = x.seen[0]
            _, n, b, f = _fields(c)
            name, col = F.lit(x.names[0]), F.lit(c.col)
            texts = F.transform(F.map_entries("texts"), lambda e: F.struct(name, col, e["key"], e["value"], F.lit(None), F.lit(None), F.lit(None))).cast(one)
            rows = F.concat(F.coalesce(texts, F.array().cast(one)), F.array(F.struct(name, col, F.lit(""), void, n, b, f).cast(one[6:-1])))
            parts.append(x.df.select(F.inline(rows), "w"))
        kind = F.when(F.col("b").isNotNull(), "B").when(F.col("n").isNotNull(), "N").when(F.col("s").isNotNull(), "S")
        out += [p.withColumn("kind", kind).where(F.col("kind").isNotNull()) for p in parts]
    values = [value_dictionary(reduce(DataFrame.unionByName, out), F.col("w"))] if out else []
    return keep(reduce(DataFrame.unionByName, values + [x for x in numbers if x is not None]))


Mapping = dict[tuple[str, str], dict[str | None, list[tuple[str, bool]]]]


def mapping(nodes: DataFrame) -> Mapping:
    """Templates in order by (sheet, column) and style: a few rows a column."""
    out: Mapping = {}
    for r in nodes.select("sheet_id", "col", "style_key", "level", "template", "loose").orderBy("level").collect():
        out.setdefault((r.sheet_id, r.col), {}).setdefault(r.style_key, []).append((r.template, r.loose))
    return out


# ---- counts


def _size(t: str, c: Cell) -> Column:
    """How many different objects a covered cell has; most templates always have one."""
    s, _, b, _ = _fields(c)
    if t in ("T13", "T14", "T15", "T15t"):
        some = _there(c)
    elif t == "T12":
        some = b.isNotNull()
    elif t == "T10":
        some = s.isNotNull()
    elif t == "T9":
        some = s.isNotNull() | _there(c) | b.isNotNull()
    elif t in LISTS:
        return F.coalesce(F.size(_all(t, c)), F.lit(0))
    elif c.s is None:
        some = _there(c)
    else:
        some = _there(c) | _one(t, c, False).isNotNull()
    return F.when(some, 1).otherwise(0)


def _one(t: str, c: Cell, loose: bool) -> Column:
    return F.get(execute.object_cases(*_fields(c)[:3], F.lit(loose))[t](), F.lit(0))


def _all(t: str, c: Cell, loose: bool = False) -> Column:
    return F.array_distinct(F.filter(execute.object_cases(*_fields(c)[:3], F.lit(loose))[t](), lambda x: x.isNotNull()))


def _covered(t: str, c: Cell, loose: bool, mode: str) -> Column:
    s, n, b, f = _fields(c)

    def bit(name: str) -> Column:
        if name in ("whole", "fraction"):
            return F.lit(False) if c.n is None else number_mask(n) == BITS[name]
        return F.lit(False) if c.s is None else text_tests(s)[name]()

    return F.coalesce(execute.cover_cases(s.isNotNull(), _there(c), b.isNotNull(), f, bit, F.lit(loose), mode)[t](), F.lit(False))


def _met(t: str, c: Cell, loose: bool, goal: str, clean: Cell) -> Column:
    """Objects that the best match of the two predicates makes meet, both cells being covered."""
    if t in IRI or goal in IRI:
        return F.least(_size(t, c), _size(goal, clean)) if t in IRI and goal in IRI else F.lit(0)
    if TEMPLATES[t].datatype != TEMPLATES[goal].datatype:
        return F.lit(0)
    if t == goal and c is clean and t in ("T9", "T12", "T13", "T14", "T15", "T15t"):
        return _size(t, c)  # one expression over one cell
    if t in LISTS or goal in LISTS:
        return F.coalesce(F.size(F.array_intersect(_all(t, c, loose), _all(goal, clean, True))), F.lit(0))
    return F.when(_one(t, c, loose) == _one(goal, clean, True), 1).otherwise(0)


def by_mapping(c: Cell, clean: Cell, goal: str, styles: dict[str | None, list[tuple[str, bool]]], texts: Column | None, mode: str) -> Counts:
    """A cell under its mapping. texts: by style, where the column is styled."""
    sizes, met = [], []
    expected = _covered(goal, clean, True, "calibrated")
    for key, objects in styles.items():
        part = c
        if texts is not None:
            part = Cell(c.sheet, c.col, F.try_element_at(texts, F.lit(key)), fmt=c.fmt, **({"n": c.n, "b": c.b} if key == "" else {}))
        size, meet = F.lit(0), F.lit(0)
        for t, loose in reversed(objects):
            covered = _covered(t, part, loose, mode)
            exact = F.when(_one("T8", part, loose).isNotNull(), 1).otherwise(0) if t == "T8" else _size(t, part)
            size = F.when(covered, exact).otherwise(size)
            meet = F.when(covered, _met(t, part, loose, goal, clean)).otherwise(meet)
        sizes.append(size)
        met.append(F.when(expected, meet).otherwise(0))
    na = reduce(Column.__add__, sizes) if sizes else F.lit(0)
    tp = F.greatest(*met) if len(met) > 1 else met[0] if met else F.lit(0)
    return tp, na, F.when(expected, _size(goal, clean)).otherwise(0)


def by_rendering(c: Cell, clean: Cell, goal: str, how: str) -> Counts:
    """A cell under the flat extractor: its value's statement, and the one that names the column."""
    s, n, b, _ = _fields(c)
    dated = how == "display" and c.fmt in ("date", "datetime")
    expected, datatype = _covered(goal, clean, True, "calibrated"), TEMPLATES[goal].datatype
    # a number on its own need not be made into text: any has a look, a date one within the calendar
    there = b.isNotNull() | (X.on_calendar(n).isNotNull() if dated else _there(c))
    same, v = F.lit(False), None
    # the look gives no other datatype that a template has; whole numbers look like themselves
    asked = goal in IRI or datatype in ("xsd:integer", "xsd:string")
    own = goal == "T13" and c is clean and c.b is None and not dated
    if c.s is not None or asked and goal not in IRI and not (own and c.whole):
        texts = [] if c.s is None else [F.when(s.contains("<"), F.regexp_replace(s, "<[^>]*>", "")).otherwise(s)]
        if c.b is not None:
            texts.append(F.when(b.isNotNull(), F.when(b, "Yes").otherwise("No") if how == "display" else b.cast("int").cast("string")))
        if c.n is not None:
            texts.append(X.decimal_text(n) if not dated else X.serial_date(n) if c.fmt == "date" else X.serial_datetime(n))
        v = F.coalesce(*texts)
    if c.s is not None:
        there = F.coalesce(v != "", F.lit(False))
    if asked and v is not None:
        iri = v.startswith("http://") | v.startswith("https://")
        if goal in IRI:
            same = iri & (_size(goal, clean) > 0)
        else:
            look = F.when(v.rlike(X.INT), "xsd:integer").when(v.rlike(X.DECIMAL_POINT), "xsd:float").otherwise("xsd:string")
            e = _one(goal, clean, True)
            same = ~iri & (v == e) & (look == datatype)
            same = F.coalesce(same, F.lit(False)) | (e == F.lit(c.col) if datatype == "xsd:string" else F.lit(False))
            if own:  # here of up to 15 digits
                same = F.when((F.abs(n) < 1e15) & (n == F.floor(n)), True).otherwise(same)
    elif own and c.whole:
        same = F.lit(True)
    return F.when(there & expected & same, 1).otherwise(0), F.when(there, 2).otherwise(0), F.when(expected, _size(goal, clean)).otherwise(0)


def sums(df: DataFrame, runs: dict[str, list[Counts]], weight: Column | None = None) -> DataFrame:
    """tp, fp, fn of each run over one table; counts that runs share, as one object, are made once."""
    each = list({id(x): x for counts in runs.values() for x in counts}.items())
    at = {key: k for k, (key, _) in enumerate(each)}
    total = df.agg(*[F.coalesce(F.sum(x[j] if weight is None else x[j] * weight), F.lit(0)).alias(f"{name}{k}") for k, (_, x) in enumerate(each) for j, name in enumerate(("tp", "na", "ne"))])
    rows = []
    for run, counts in runs.items():
        tp, na, ne = (F.expr(" + ".join(f"{name}{at[id(x)]}" for x in counts)) for name in ("tp", "na", "ne"))
        rows.append(F.struct(F.lit(run).alias("sheet_id"), tp.alias("tp"), (na - tp).alias("fp"), (ne - tp).alias("fn")))
    return total.select(F.inline(F.array(*rows))).where("tp + fp + fn > 0")


def _goal(c: Cell) -> str:
    t = truth.EXPECTED[c.sheet][c.col]
    return "T14" if t == "N" else t


# ---- whole runs

#: Templates that do not read a text to count its objects.
UNREAD = ("T9", "T10", "T12", "T13", "T14", "T15", "T15t")


def _by_text(sheet: Sheet, chosen: Mapping) -> list[Sheet]:
    """The sheet in parts: its columns whose texts are read, each as its different pairs of cells, w times each; the rest by row."""
    rest, out = [], []
    for c, clean, name, runs in sheet.cells():
        used = {t for _, trees in runs for objects in chosen.get((trees, c.col), {}).values() for t, _ in objects}
        if clean.s is None or used <= set(UNREAD):
            rest.append((c, clean, name, runs))
            continue
        columns, cells = [], []
        for side, x in (("x", c), ("y", clean)):
            if side == "y" and x is c:
                cells.append(cells[0])
                continue
            new = {f: getattr(x, f) for f in ("s", "n", "b") if getattr(x, f) is not None}
            columns += [v.alias(side + f) for f, v in new.items()]
            cells.append(Cell(x.sheet, x.col, fmt=x.fmt, **{f: F.col(side + f) for f in new}))
        pairs = sheet.df.select(*columns, _times(sheet.df).alias("w"))
        out.append(Sheet(sheet.name, pairs.groupBy(*pairs.columns[:-1]).agg(F.sum("w").alias("w")), (cells[0],), (cells[1],), (name,), (runs,)))
    if rest:
        out.append(Sheet(sheet.name, sheet.df, *zip(*rest)))
    return out


def count_predicted(sheets: list[Sheet], nodes: DataFrame | Mapping, styled: set[tuple[str, str]], mode: str) -> DataFrame:
    """Sums by run of the statements under a mapping."""
    chosen, out = nodes if isinstance(nodes, dict) else mapping(nodes), []
    for sheet in sheets:
        for x in (*_by_text(_staged(sheet, styled), chosen), *_styled(sheet, styled)):
            texts = F.col("texts") if "texts" in x.df.columns else None
            runs: dict[str, list[Counts]] = {}
            for c, clean, _, uses in x.cells():
                made: dict[str, Counts] = {}  # by mapping: runs that map a column alike share its counts
                for run, trees in uses:
                    styles = chosen.get((trees, c.col), {})
                    if repr(styles) not in made:
                        made[repr(styles)] = by_mapping(c, clean, _goal(clean), styles, texts, mode)
                    runs.setdefault(run, []).append(made[repr(styles)])
            if runs:
                out.append(sums(x.df, runs, F.col("w") if "w" in x.df.columns else None))
    return reduce(DataFrame.unionByName, out)


def count_rendered(spark: SparkSession, sf_dir: str, name: str, runs: dict[str, Callable[[Cell], Cell]], how: str) -> DataFrame:
    """Sums by run of the flat extractor's statements over one table; a column that a run leaves alone is counted once for all."""
    df, clean = read(spark, sf_dir, name)
    plain = {c.col: by_rendering(c, c, _goal(c), how) for c in clean}
    return sums(df, {run: [plain[c.col] if seen is c else by_rendering(seen, c, _goal(c), how) for c in clean for seen in [change(c)]] for run, change in runs.items()})


def plain_sheets(spark: SparkSession, sf_dir: str, names: tuple[str, ...], change: Callable[[Cell], Cell] = lambda c: c, tag: str = "") -> list[Sheet]:
    out = []
    for name in names:
        df, clean = read(spark, sf_dir, name)
        out.append(Sheet(tag + name, df, tuple(change(c) for c in clean), clean))
    return out


def graded(counts: DataFrame) -> DataFrame:
    return match.ratios(counts.groupBy("sheet_id").agg(*[F.sum(c).cast("long").alias(c) for c in ("tp", "fp", "fn")]))


def expected_mapping(names: tuple[str, ...]) -> Mapping:
    """`truth.expected_mapping` as templates by column."""
    return {(s, c): {None: [("T14" if t == "N" else t, True)]} for s in names for c, t in truth.EXPECTED[s].items()}


def grade_predicted(spark: SparkSession, sf_dir: str, names: tuple[str, ...], mode: str = "literal", **args) -> DataFrame:
    """Predicted and graded by sheet, without styles. args: of `tree.build`."""
    sheets = plain_sheets(spark, sf_dir, names)
    return graded(count_predicted(sheets, tree.build_from(dictionary(sheets, set()), mode, **args), set(), mode))
