"""Column profiles: all that the heuristics need, from one pass over the cells and two dictionaries.

Which templates can cover a cell depends on its kind, format and text only, so cells fall into a few
classes a column, and counts, unique and distinct texts add up over classes. Tokens of one spelling may
come from several classes; they are summed up by the pattern of classes they occur in.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sheetgraph.functions import text as X

COLUMN = ("sheet_id", "col", "style_key")
#: Bits of a class: what its texts parse as, or what its numbers look like.
BITS = {"int": 1, "point": 2, "comma": 4, "date": 8, "datetime": 16, "list": 32, "word": 64, "whole": 128, "fraction": 256}


def text_tests(s: Column) -> dict[str, Callable[[], Column]]:
    """What a text parses as, by the name of the bit; each is made when called."""

    def whole_numbers() -> Column:
        parts = X.tokens(s)
        return s.rlike("[0-9]") & (F.size(parts) > 0) & F.forall(parts, lambda t: t.rlike(X.INT))

    return {
        "int": lambda: s.rlike(X.INT),
        "point": lambda: s.rlike(X.DECIMAL_POINT),
        "comma": lambda: s.rlike(X.DECIMAL_COMMA),
        "date": lambda: X.date_text(s).isNotNull(),
        "datetime": lambda: X.datetime_text(s).isNotNull(),
        "list": whole_numbers,
        "word": lambda: (F.length(s) <= 64) & X.parse_boolean(F.when(F.length(s) <= 64, s)).isNotNull(),
    }


def text_mask(s: Column) -> Column:
    out = F.lit(0)
    for name, test in text_tests(s).items():
        out = out + F.when(test(), BITS[name]).otherwise(0)
    return out


def number_mask(n: Column) -> Column:
    return F.when(n == F.floor(n), BITS["whole"]).otherwise(BITS["fraction"])


def value_dictionary(cells: DataFrame, times: Column | None = None) -> DataFrame:
    """Distinct texts with their counts and masks; numbers and booleans only as counts by class. times: how often a row counts."""
    number = F.when(F.col("kind") == "N", number_mask(F.col("n")))
    text = F.when(F.col("kind") == "S", F.col("s"))
    grouped = cells.groupBy(*COLUMN, "kind", "format_class", number.alias("number_mask"), text.alias("value")).agg((F.count(F.lit(1)) if times is None else F.sum(times)).alias("cnt"))
    mask = F.when(F.col("kind") == "S", text_mask(F.col("value"))).otherwise(F.coalesce("number_mask", F.lit(0)))
    return grouped.withColumn("mask", mask.cast("int")).drop("number_mask")


def classes(values: DataFrame) -> DataFrame:
    """Cells, unique texts, distinct texts and total text length, by column and class."""
    is_text = F.col("kind") == "S"
    return values.groupBy(*COLUMN, "kind", "format_class", "mask").agg(
        F.sum("cnt").alias("cells"),
        F.count_if(is_text & (F.col("cnt") == 1)).alias("singles"),
        F.count_if(is_text).alias("texts"),
        F.coalesce(F.sum(F.when(is_text, F.col("cnt") * F.length("value"))), F.lit(0)).alias("length"),
    )


def token_dictionary(values: DataFrame, space: bool = False) -> DataFrame:
    """Separated parts of the texts, by column and class of the text."""
    rows = values.where(F.col("kind") == "S").select(*COLUMN, "mask", "cnt", F.explode(X.tokens(F.col("value"), space)).alias("token"))
    return rows.groupBy(*COLUMN, "token", "mask").agg(F.sum("cnt").alias("cnt"))


def token_patterns(tokens: DataFrame) -> DataFrame:
    """How many different tokens occur once or more often in which classes, with their total counts."""
    one = F.struct("mask", F.least("cnt", F.lit(2)).alias("times"), "cnt")
    whole = tokens.groupBy(*COLUMN, "token").agg(F.sort_array(F.collect_list(one)).alias("at"))
    whole = whole.withColumn("is_int", F.col("token").rlike(X.INT)).withColumn("pattern", F.transform("at", lambda x: F.struct(x["mask"], x["times"])))
    cnts = whole.groupBy(*COLUMN, "pattern", "is_int")
    return cnts.agg(F.count(F.lit(1)).alias("tokens"), F.sum(F.aggregate("at", F.lit(0).cast("long"), lambda a, x: a + x["cnt"])).alias("cnt"))


def token_counts(tokens: DataFrame) -> DataFrame:
    """Token occurrences, and whole numbers among them, by column and class."""
    return tokens.groupBy(*COLUMN, "mask").agg(F.sum("cnt").alias("t"), F.sum(F.when(F.col("token").rlike(X.INT), F.col("cnt")).otherwise(0)).alias("t_int"))


def has(mask: Column, bit: str) -> Column:
    return mask.bitwiseAND(F.lit(BITS[bit])) != 0


def column_profile(cells: DataFrame, with_tokens: bool = True) -> DataFrame:
    """One row for each column: the counts in the heuristics' formulas."""
    values = value_dictionary(cells)
    m, k, c = F.col("mask"), F.col("kind"), F.col("cells")

    def total(test: Column) -> Column:
        return F.coalesce(F.sum(F.when(test, c)), F.lit(0)).cast("long")

    s = k == "S"
    base = classes(values).groupBy(*COLUMN).agg(
        F.sum("cells").cast("long").alias("c"),
        total(s).alias("s"),
        total(k == "N").alias("n"),
        total(k == "B").alias("b"),
        F.sum("singles").cast("long").alias("u_s"),
        F.sum("texts").cast("long").alias("p_s"),
        F.sum("length").cast("long").alias("len"),
        *[total(s & has(m, bit)).alias(f"s_{bit}") for bit in ("int", "point", "comma", "date", "datetime")],
        total((k == "N") & has(m, "whole")).alias("n_whole"),
        total((k == "N") & has(m, "fraction")).alias("n_fraction"),
        *[total((k == "N") & (F.col("format_class") == f)).alias(f"n_{f}") for f in ("date", "datetime")],
    )
    if not with_tokens:
        return base
    tokens = values.where(s).select(*COLUMN, "cnt", F.explode(X.tokens(F.col("value"))).alias("token"))
    tokens = tokens.groupBy(*COLUMN, "token").agg(F.sum("cnt").alias("cnt"))
    per = tokens.groupBy(*COLUMN).agg(
        F.sum("cnt").cast("long").alias("t"),
        F.coalesce(F.sum(F.when(F.col("token").rlike(X.INT), F.col("cnt"))), F.lit(0)).cast("long").alias("t_int"),
        F.count_if(F.col("cnt") == 1).cast("long").alias("u_t"),
        F.count(F.lit(1)).cast("long").alias("p_t"),
    )
    same = [base[x].eqNullSafe(per[x]) for x in COLUMN]
    joined = base.join(per, same[0] & same[1] & same[2], "left")
    return joined.select(*[base[x] for x in base.columns], *[F.coalesce(per[x], F.lit(0)).alias(x) for x in ("t", "t_int", "u_t", "p_t")])
