"""The fifteen templates: score, rank and what each one covers, from a column's profile."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sheetgraph.operators.profile import COLUMN, column_profile

#: Mean text length under which a column of at most two texts is boolean, and the sums' rounding.
BOOLEAN_LENGTH, DIGITS = 3.5, 12
MODES = ("literal", "guarded", "calibrated")


@dataclass(frozen=True)
class Template:
    """A template's fixed choices. order: place among equals of one rank, smaller first."""

    id: str
    name: str
    rank: int
    reference: str
    term: str
    datatype: str
    function: str
    order: int


# Fixed values of the templates
TEMPLATES = {
    t.id: t
    for t in (
        Template("T1", "formatted text", 9, "valueRichText", "child", "child", "styled", 0),
        Template("T2", "integer in text", 2, "json", "literal", "xsd:integer", "parseNumber", 12),
        Template("T3", "decimal in text, point", 1, "json", "literal", "xsd:decimal", "parseNumber", 13),
        Template("T4", "decimal in text, comma", 1, "json", "literal", "xsd:decimal", "parseNumber", 14),
        Template("T5", "date in text", 2, "json", "literal", "xsd:date", "parseDate", 15),
        Template("T6", "date-time in text", 3, "json", "literal", "xsd:dateTime", "parseDateTime", 16),
        Template("T7", "integer list in text", 0, "json", "literal", "xsd:integer", "parseNumber", 17),
        Template("T8", "boolean in text", 4, "json", "literal", "xsd:boolean", "parseBoolean", 11),
        Template("T9", "string", 0, "value", "literal", "xsd:string", "", 18),
        Template("T10", "single entity", 3, "valueString", "iri", "", "entityLinking", 19),
        Template("T11", "multiple entities", 4, "valueString", "iri", "", "entityLinking", 20),
        Template("T12", "native boolean", 0, "valueBoolean", "literal", "xsd:boolean", "", 1),
        Template("T13", "native integer", 3, "valueInt", "literal", "xsd:integer", "", 2),
        Template("T14", "native decimal", 4, "valueNumeric", "literal", "xsd:decimal", "", 3),
        Template("T15", "number with date format", 5, "json", "literal", "xsd:date", "parseDate", 4),
        Template("T15t", "number with date-time format", 5, "json", "literal", "xsd:dateTime", "parseDateTime", 5),
    )
}
# end of fixed values


@dataclass(frozen=True)
class Registered:
    """A template of the user's own: how it scores a column, which classes of cells it covers, what it makes.

    score: of the live classes of a column, dicts with kind, format_class, mask, cells, singles, texts, length.
    covers: of kind, format class and mask, on values; applies: the same as a column over cells with a mask.
    objects: column over cells, an array of lexical forms.
    """

    template: Template
    score: Callable[[list[dict]], float]
    covers: Callable[[str, str | None, int], bool]
    applies: Callable[[], Column]
    objects: Callable[[], Column]


REGISTERED: dict[str, Registered] = {}


def register(entry: Registered) -> None:
    """Let trees choose, and mappings run, a further template; an id can be taken once."""
    if entry.template.id in TEMPLATES or entry.template.id in REGISTERED:
        raise ValueError(f"template {entry.template.id} is there already")
    REGISTERED[entry.template.id] = entry


def template_of(id_: str) -> Template:
    return REGISTERED[id_].template if id_ in REGISTERED else TEMPLATES[id_]


def all_templates() -> list[Template]:
    return [*TEMPLATES.values(), *(x.template for x in REGISTERED.values())]


def dup(c: Column, u: Column, p: Column) -> Column:
    """Degree of duplication: half how many elements recur, half how uniform they are; 0 up to one element."""
    c = c.cast("double")
    return F.when(c <= 1, F.lit(0.0)).otherwise((2 * c - u - p + 1) / (2 * c))


def _share(x: Column, of: Column) -> Column:
    return F.coalesce(F.try_divide(x.cast("double"), of.cast("double")), F.lit(0.0))


def score_columns(mode: str = "literal") -> dict[str, Column]:
    """Score of each template over the columns of a profile."""
    if mode not in MODES:
        raise ValueError(f"mode is one of {MODES}")
    g = F.col
    o = g("n") + g("b")
    dates = g("n") if mode == "literal" else F.when(g("s_date") + g("s_datetime") > 0, g("n")).otherwise(g("n_date") + g("n_datetime"))
    whole = dup(g("c"), g("u_s") + o, g("p_s") + o)
    texts = dup(g("s"), g("u_s"), g("p_s"))
    boolean = (g("p_s").between(1, 2)) & (_share(g("len"), g("s")) < BOOLEAN_LENGTH)
    out = {
        "T2": _share(g("s_int") + g("n_whole"), g("c")),
        "T3": _share(g("s_point") + g("n_fraction"), g("c")),
        "T4": _share(g("s_comma") + g("n_fraction"), g("c")),
        "T5": _share(g("s_date") + dates, g("c")),
        "T6": _share(g("s_datetime") + dates, g("c")),
        "T7": _share(g("t_int"), g("t")),
        "T8": F.when(boolean, _share(g("s"), g("c"))).otherwise(0.0),
        "T9": 1 - whole,
        "T10": F.when(g("s") > 0, whole).otherwise(0.0),
        "T11": F.when(g("s") > 0, dup(g("t") + o, g("u_t") + o, g("p_t") + o)).otherwise(0.0),
        "T12": _share(g("b"), g("c")),
        "T13": _share(g("n_whole"), g("c")),
        "T14": _share(g("n_fraction"), g("c")),
        "T15": _share(g("n_date"), g("c")),
        "T15t": _share(g("n_datetime"), g("c")),
    }
    if mode == "calibrated":
        out["T9"] = _share(g("s"), g("c")) * (1 - texts)
        out["T10"] = _share(g("s"), g("c")) * texts
        out["T13"] = F.when(g("n_fraction") == 0, _share(g("n"), g("c"))).otherwise(0.0)
        out["T14"] = F.when(g("n_fraction") > 0, _share(g("n"), g("c"))).otherwise(0.0)
        out["T2"] = F.when(g("n_fraction") == 0, out["T2"]).otherwise(_share(g("s_int"), g("c")))
    return out


def scores(profile: DataFrame, mode: str = "literal") -> DataFrame:
    """A row for each column and template: score, rank, place among equals."""
    rows = [F.struct(F.lit(t).alias("template"), F.round(s, DIGITS).alias("score"), F.lit(TEMPLATES[t].rank).alias("rank"), F.lit(TEMPLATES[t].order).alias("place")) for t, s in score_columns(mode).items()]
    return profile.select(*COLUMN, F.inline(F.array(*rows)))


def pick(scored: DataFrame) -> DataFrame:
    """The template with the highest score; the greater rank, then the smaller place decide ties."""
    best = F.max_by(F.struct("template", "score", "rank"), F.struct("score", "rank", -F.col("place")))
    out = scored.where(F.col("score") > 0).groupBy(*COLUMN).agg(best.alias("best"))
    return out.select(*COLUMN, "best.template", "best.score", "best.rank")


def dup_degree(df: DataFrame, column: str) -> DataFrame:
    """c, u, p and dup of one text column, through its dictionary."""
    counts = df.where(F.col(column).isNotNull() & (F.col(column) != "")).groupBy(column).agg(F.count(F.lit(1)).alias("cnt"))
    got = counts.agg(F.coalesce(F.sum("cnt"), F.lit(0)).alias("c"), F.count_if(F.col("cnt") == 1).alias("u"), F.count(F.lit(1)).alias("p"))
    return got.withColumn("dup", F.round(dup(F.col("c"), F.col("u"), F.col("p")), 6))


def predict_roots(cells: DataFrame, mode: str = "literal") -> DataFrame:
    """The root of each column's tree: the one way templates are chosen."""
    from sheetgraph.operators import tree

    return tree.build(cells, mode, max_depth=1).select(*COLUMN, "template", "score", "rank")
