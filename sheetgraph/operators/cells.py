"""Cells: one row for each non-blank cell of a sheet, with its kind, value and number format."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sheetgraph.functions import text as X

CELL_COLUMNS = ("sheet_id", "row_id", "col", "style_key", "kind", "s", "n", "b", "format_class", "rich")


@dataclass(frozen=True)
class SheetSpec:
    """How a table reads as a sheet: its key, columns to show, and number formats (date, datetime, bool)."""

    sheet_id: str
    key: tuple[str, ...]
    formats: dict[str, str] = field(default_factory=dict)
    rich: tuple[str, ...] = ()
    columns: tuple[str, ...] | None = None


def row_id(spec: SheetSpec) -> Column:
    return F.concat_ws("-", *[F.col(f"`{k}`").cast("string") for k in spec.key])


def _cell(name: str, kind: T.DataType, spec: SheetSpec) -> Column:
    c, fmt = F.col(f"`{name}`"), spec.formats.get(name)
    text = number = F.lit(None)
    flag = F.lit(None)
    if isinstance(kind, T.StringType):
        text = F.nullif(c, F.lit(""))
    elif isinstance(kind, T.BooleanType):
        flag = c
    elif isinstance(kind, (T.TimestampType, T.TimestampNTZType, T.DateType)):
        number, fmt = X.serial_of(c), fmt or ("date" if isinstance(kind, T.DateType) else "datetime")
    elif isinstance(kind, T.NumericType):
        number = c.cast("double")
    else:
        raise TypeError(f"column {name} of type {kind.simpleString()} has no place in a sheet")
    if fmt == "bool":  # numbers under a yes/no format are booleans
        flag, number = F.coalesce(flag, number != 0), F.lit(None)
    rich = text if name in spec.rich else F.lit(None)
    return F.struct(
        F.lit(name).alias("col"),
        text.cast("string").alias("s"),
        number.cast("double").alias("n"),
        flag.cast("boolean").alias("b"),
        F.lit(fmt if fmt in ("date", "datetime") else None).cast("string").alias("format_class"),
        rich.cast("string").alias("rich"),
    )


def from_table(df: DataFrame, spec: SheetSpec) -> DataFrame:
    """All cells of a table in one pass over it; blank cells are no cells."""
    names = spec.columns or tuple(df.columns)
    types = {f.name: f.dataType for f in df.schema.fields}
    wide = df.select(row_id(spec).alias("row_id"), F.inline(F.array(*[_cell(n, types[n], spec) for n in names])))
    kind = F.when(F.col("b").isNotNull(), "B").when(F.col("n").isNotNull(), "N").when(F.col("s").isNotNull(), "S")
    out = wide.withColumn("kind", kind).where(F.col("kind").isNotNull())
    return out.withColumn("sheet_id", F.lit(spec.sheet_id)).withColumn("style_key", F.lit(None).cast("string")).select(*CELL_COLUMNS)


#: The twelve stand-ins for portal sheets: every scalar table of the given data.
PORTAL = (
    SheetSpec("region", ("r_regionkey",)),
    SheetSpec("nation", ("n_nationkey",)),
    SheetSpec("customer", ("c_custkey",)),
    SheetSpec("supplier", ("s_suppkey",)),
    SheetSpec("part", ("p_partkey",)),
    SheetSpec("orders", ("o_orderkey",), {"o_orderdate": "date"}),
    SheetSpec("lineitem", ("l_orderkey", "l_linenumber", "ordinal"), {"l_shipdate": "date"}, columns=("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate")),
    SheetSpec("events", ("event_id",), {"ts": "datetime"}),
    SheetSpec("documents", ("doc_id",)),
    SheetSpec("pages", ("page_id",)),
    SheetSpec("labels", ("doc_id",), {"quality": "bool", "toxic": "bool"}),
    SheetSpec("conversations", ("conv_id", "turn")),
)
SPECS = {s.sheet_id: s for s in PORTAL}


def read_sheet(spark, sf_dir: str, name: str) -> DataFrame:
    """A given table as a wide sheet; line items get an ordinal, as their key has repeats."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if name == "lineitem":
        from pyspark.sql import Window

        rest = [c for c in df.columns if c not in ("l_orderkey", "l_linenumber")]
        w = Window.partitionBy("l_orderkey", "l_linenumber").orderBy(*rest)
        df = df.withColumn("ordinal", F.row_number().over(w))
    return df


def portal_cells(spark, sf_dir: str, names: tuple[str, ...] = tuple(SPECS)) -> DataFrame:
    out = None
    for name in names:
        cells = from_table(read_sheet(spark, sf_dir, name), SPECS[name])
        out = cells if out is None else out.unionByName(cells)
    return out
