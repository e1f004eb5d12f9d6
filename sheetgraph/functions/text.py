"""Reading values out of cell text, as column expressions: predicates, numbers, dates, booleans, tokens."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

INT = r"^[+-]?[0-9]+$"
DECIMAL_POINT = r"^[+-]?[0-9]+\.[0-9]+$"
DECIMAL_COMMA = r"^[+-]?[0-9]+,[0-9]+$"
#: Delimiters between the separated parts of a text: runs that are neither letter, digit nor white space.
DELIMITER = r"[^\p{L}\p{N}\s]+"

# Month names in English and German, by number
MONTHS = {
    1: ("january", "jan", "januar"),
    2: ("february", "feb", "februar"),
    3: ("march", "mar", "märz"),
    4: ("april", "apr"),
    5: ("may", "mai"),
    6: ("june", "jun", "juni"),
    7: ("july", "jul", "juli"),
    8: ("august", "aug"),
    9: ("september", "sep"),
    10: ("october", "oct", "oktober", "okt"),
    11: ("november", "nov"),
    12: ("december", "dec", "dezember", "dez"),
}
# Words that stand for true and for false
TRUE_WORDS = ("true", "yes", "y", "x", "1", "ja", "j", "wahr", "on")
FALSE_WORDS = ("false", "no", "n", "0", "nein", "falsch", "off")
# end of fixed values

#: Day 0 of a spreadsheet's calendar.
EPOCH = "1899-12-30 00:00:00"
NAMES = "|".join(sorted((n for names in MONTHS.values() for n in names), key=len, reverse=True))
TIME = r"([0-9]{1,2}):([0-9]{2})(?::([0-9]{2}))?(?: ?([AaPp])\.?[Mm]\.?)?"
#: Date forms and which groups hold year, month, day; slashes are month first, dots day first.
DATE_FORMS = (
    (r"([0-9]{4})-([0-9]{1,2})-([0-9]{1,2})", (1, 2, 3)),
    (r"([0-9]{1,2})/([0-9]{1,2})/([0-9]{4})", (3, 1, 2)),
    (r"([0-9]{1,2})\.([0-9]{1,2})\.([0-9]{4})", (3, 2, 1)),
    (rf"([0-9]{{1,2}})\. ({NAMES}) ([0-9]{{4}})", (3, 2, 1)),
    (rf"({NAMES}) ([0-9]{{1,2}}), ([0-9]{{4}})", (3, 1, 2)),
    (rf"({NAMES}) ([0-9]{{1,2}}) ([0-9]{{4}})", (3, 1, 2)),
)


def _date_of(text: Column, before: str, after: str) -> Column:
    """ISO date of the first form that matches between the two patterns, if it is a day of the calendar."""
    low, raw = F.lower(text), None
    for form, (y, m, d) in DATE_FORMS:
        pattern = before + form + after
        ordered = F.regexp_replace(low, "(?s)^.*?" + pattern + ".*$", f"${y}|${m}|${d}")
        raw = F.when(low.rlike(pattern), ordered) if raw is None else raw.when(low.rlike(pattern), ordered)
    months = F.create_map(*[F.lit(x) for number, names in MONTHS.items() for name in names for x in (name, f"{number:02d}")])

    def day(parts: Column) -> Column:
        month = F.coalesce(F.element_at(months, parts[1]), F.lpad(parts[1], 2, "0"))
        return F.concat_ws("-", parts[0], month, F.lpad(parts[2], 2, "0")).try_cast("date").cast("string")

    # in an array of one, so that the forms stand in the plan once
    return F.get(F.transform(F.array(F.split(raw, r"\|")), day), F.lit(0))


def date_text(text: Column) -> Column:
    """The whole text as a date, YYYY-MM-DD, or null."""
    return F.when(text.rlike("[0-9]"), _date_of(F.trim(text), "^", "$"))


def find_date(text: Column) -> Column:
    """The first date found anywhere in the text."""
    return F.when(text.rlike("[0-9]"), _date_of(text, "(?<![0-9a-z])", "(?![0-9])"))


def datetime_text(text: Column) -> Column:
    """The whole text as a date with time, YYYY-MM-DDTHH:MM:SS, or null."""
    t = F.trim(text)
    pattern = "^(.+?)[ Tt,]+" + TIME + "$"
    day = date_text(F.regexp_extract(t, pattern, 1))
    hour, minute = (F.regexp_extract(t, pattern, k).try_cast("int") for k in (2, 3))
    second = F.coalesce(F.regexp_extract(t, pattern, 4).try_cast("int"), F.lit(0))
    half = F.lower(F.regexp_extract(t, pattern, 5))
    hour = F.when(half == "", hour).when(hour.between(1, 12), F.pmod(hour, F.lit(12)) + F.when(half == "p", 12).otherwise(0))
    clock = F.format_string("%02d:%02d:%02d", hour, minute, second)
    return F.when(t.rlike(pattern) & day.isNotNull() & (hour < 24) & (minute < 60) & (second < 60), F.concat(day, F.lit("T"), clock))


def on_calendar(n: Column) -> Column:
    """The day number where it is in the years 1 to 9999, else null."""
    return F.when(n.between(-693_593, 2_958_465), n)


def serial_datetime(n: Column) -> Column:
    """A spreadsheet's day number as date with time, rounded to the second; no time zone has a part in it."""
    n = on_calendar(n)
    seconds = F.round(n * 86400).cast("long")
    return F.replace(F.timestamp_add("SECOND", seconds, F.lit(EPOCH).cast("timestamp_ntz")).cast("string"), F.lit(" "), F.lit("T"))


def serial_date(n: Column) -> Column:
    return F.date_format(F.date_add(F.lit("1899-12-30").cast("date"), F.floor(on_calendar(n)).cast("int")), "yyyy-MM-dd")


def serial_of(ts: Column) -> Column:
    """Day number of a timestamp without zone."""
    since = ts.cast("timestamp_ntz") - F.lit(EPOCH).cast("timestamp_ntz")
    day, hour, minute, second = (F.extract(F.lit(x), since).cast("double") for x in ("DAY", "HOUR", "MINUTE", "SECOND"))
    return day + (hour * 3600 + minute * 60 + second) / 86400


def decimal_text(n: Column) -> Column:
    """Shortest decimal form of a double, without exponent or trailing zeros."""
    plain = F.coalesce(n.try_cast("decimal(38,12)").cast("string"), n.cast("string"))  # beyond 26 digits as Spark prints it
    return F.regexp_replace(F.regexp_replace(plain, r"(\.[0-9]*?)0+$", "$1"), r"\.$", "")


def decimal_places(n: Column) -> Column:
    t = decimal_text(n)
    return F.when(t.contains("."), F.length(t) - F.instr(t, ".")).otherwise(0)


def tokens(text: Column, space: bool = False) -> Column:
    """Separated parts of a text, trimmed, without empty ones."""
    parts = F.split(text, r"[^\p{L}\p{N}]+" if space else DELIMITER)
    return F.filter(F.transform(parts, lambda t: F.regexp_replace(t, r"^\s+|\s+$", "")), lambda t: t != "")


def parse_number(text: Column, sep: str = ".", integer: bool = False) -> Column:
    """First number in the text as lexical form: integers without, decimals with the given separator."""
    if integer:
        return F.nullif(F.regexp_replace(F.regexp_extract(text, r"([+-]?[0-9]+)", 1), r"^\+", ""), F.lit(""))
    found = F.regexp_extract(text, r"([+-]?[0-9]+(?:\%s[0-9]+)?)" % sep, 1)
    return F.nullif(decimal_text(F.translate(found, sep, ".").try_cast("decimal(38,12)")), F.lit(""))


def parse_numbers(text: Column) -> Column:
    """All whole numbers among the separated parts."""
    return F.transform(F.filter(tokens(text), lambda t: t.rlike(INT)), lambda t: F.regexp_replace(t, r"^\+", ""))


def parse_boolean(text: Column, true_words=TRUE_WORDS, false_words=FALSE_WORDS) -> Column:
    """Majority of the words for true and for false; a tie is null."""
    words = F.split(F.lower(F.trim(text)), r"[^\p{L}\p{N}]+")
    yes = F.size(F.filter(words, lambda w: w.isin(*true_words)))
    no = F.size(F.filter(words, lambda w: w.isin(*false_words)))
    return F.when(yes > no, F.lit(True)).when(no > yes, F.lit(False))


def slug(text: Column) -> Column:
    """The part of an entity's IRI that its label gives: lower case, percent-encoded UTF-8, so labels stay apart."""
    return F.replace(F.url_encode(F.lower(F.trim(text))), F.lit("+"), F.lit("%20"))


def entity_iri(text: Column) -> Column:
    return F.concat(F.lit("urn:sheetgraph:entity/"), slug(text))
