"""Recursive cover: the best template's cells leave, the rest is scored again, until none is left.

The recursion runs on a column's classes and token patterns, a few rows each, never on cells; columns are
independent, so it is one pass of a Python function over a row for each column.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sheetgraph.operators.heuristics import BOOLEAN_LENGTH, REGISTERED, TEMPLATES
from sheetgraph.operators.profile import BITS, COLUMN, classes, token_counts, token_dictionary, token_patterns, value_dictionary
from sheetgraph.session import prepare

NODES = "sheet_id string, col string, style_key string, level int, template string, score double, rank int, cells long, loose boolean"


def _dup(c: int, u: int, p: int) -> float:
    return (2 * c - u - p + 1) / (2 * c) if c > 1 else 0.0


def covers(template: str, kind: str, fmt: str | None, mask: int, mode: str = "literal", dated_text: bool = False, one_text: bool = False, more: dict | None = None) -> bool:
    """Whether a template can map cells of a class. more: registered templates by id."""
    if more and template in more:
        return bool(more[template].covers(kind, fmt, mask))
    text, number = kind == "S", kind == "N"
    counted = number and (mode == "literal" or dated_text or fmt in ("date", "datetime"))
    return {
        "T2": text and mask & BITS["int"] or number and mask & BITS["whole"],
        "T3": text and mask & BITS["point"] or number and mask & BITS["fraction"],
        "T4": text and mask & BITS["comma"] or number and mask & BITS["fraction"],
        "T5": text and mask & BITS["date"] or counted,
        "T6": text and mask & BITS["datetime"] or counted,
        "T7": text and mask & BITS["list"],
        "T8": text and (mask & BITS["word"] or one_text),
        "T9": True,
        "T10": text,
        "T11": text,
        "T12": kind == "B",
        "T13": number and (mask & BITS["whole"] or mode == "calibrated"),
        "T14": number and (mask & BITS["fraction"] or mode == "calibrated"),
        "T15": number and fmt == "date",
        "T15t": number and fmt == "datetime",
    }[template] not in (False, 0)


def live_scores(live: list[dict], patterns: list[dict], counts: list[dict], mode: str, more: dict | None = None) -> dict[str, float]:
    """Scores of a column's remaining classes."""

    def total(test) -> int:
        return sum(x["cells"] for x in live if test(x))

    def parsed(bit: str) -> int:
        return total(lambda x: x["kind"] == "S" and x["mask"] & BITS[bit])

    c, s, n, b = (total(lambda x, k=k: k is None or x["kind"] == k) for k in (None, "S", "N", "B"))
    whole, fraction = (total(lambda x, k=k: x["kind"] == "N" and x["mask"] & BITS[k]) for k in ("whole", "fraction"))
    by_format = {f: total(lambda x, f=f: x["kind"] == "N" and x["format_class"] == f) for f in ("date", "datetime")}
    u_s, p_s, length = (sum(x[k] for x in live) for k in ("singles", "texts", "length"))
    masks = {x["mask"] for x in live if x["kind"] == "S"}
    t = sum(x["t"] for x in counts if x["mask"] in masks)
    t_int = sum(x["t_int"] for x in counts if x["mask"] in masks)
    u_t = p_t = 0
    for x in patterns:
        times = sum(y["times"] for y in x["pattern"] if y["mask"] in masks)
        p_t += x["tokens"] * (times > 0)
        u_t += x["tokens"] * (times == 1)
    o = n + b
    dated = parsed("date") + parsed("datetime") > 0
    dates = n if mode == "literal" or dated else sum(by_format.values())
    dup, dup_s = _dup(c, u_s + o, p_s + o), _dup(s, u_s, p_s)
    out = {
        "T2": (parsed("int") + whole) / c,
        "T3": (parsed("point") + fraction) / c,
        "T4": (parsed("comma") + fraction) / c,
        "T5": (parsed("date") + dates) / c,
        "T6": (parsed("datetime") + dates) / c,
        "T7": t_int / t if t else 0.0,
        "T8": s / c if 1 <= p_s <= 2 and length / s < BOOLEAN_LENGTH else 0.0,
        "T9": 1 - dup,
        "T10": dup if s else 0.0,
        "T11": _dup(t + o, u_t + o, p_t + o) if s else 0.0,
        "T12": b / c,
        "T13": whole / c,
        "T14": fraction / c,
        "T15": by_format["date"] / c,
        "T15t": by_format["datetime"] / c,
    }
    if mode == "calibrated":
        out |= {"T9": s / c * (1 - dup_s), "T10": s / c * dup_s, "T13": n / c * (not fraction), "T14": n / c * (fraction > 0)}
        out["T2"] = out["T2"] if not fraction else parsed("int") / c
    out |= {k: x.score(live) for k, x in (more or {}).items()}
    return {k: round(v, 12) for k, v in out.items()}


def grow(live: list[dict], patterns: list[dict], counts: list[dict], mode: str = "literal", allowed: set[str] | None = None, max_depth: int = 15, forced: str | None = None, more: dict | None = None) -> list[tuple]:
    """(level, template, score, rank, cells, loose) from the root on. forced: a hint's template for the root."""
    nodes, used = [], set()
    while live and len(nodes) < max_depth:
        scores = live_scores(live, patterns, counts, mode, more)
        dated = any(x["kind"] == "S" and x["mask"] & (BITS["date"] | BITS["datetime"]) for x in live)
        one = sum(x["texts"] for x in live) == 1
        best = None
        for t, score in scores.items():
            if t in used or allowed is not None and t not in allowed or forced and not nodes and t != forced:
                continue
            taken = [x for x in live if covers(t, x["kind"], x["format_class"], x["mask"], mode, dated, one, more)]
            if taken and (score > 0 or forced == t and not nodes):
                of = more[t].template if more and t in more else TEMPLATES[t]
                key = (score, of.rank, -of.order)
                if best is None or key > best[0]:
                    best = (key, t, taken)
        if best is None:
            if forced and not nodes:
                forced = None
                continue
            break
        (score, rank, _), t, taken = best
        # whether the rest of the column, and not the cell alone, let the template cover it; execution reads it
        loose = t == "T8" and one or t in ("T5", "T6") and (dated or mode == "literal")
        nodes.append((len(nodes), t, score, rank, sum(x["cells"] for x in taken), loose))
        used.add(t)
        live = [x for x in live if x not in taken]
    return nodes


def predict_values(values: list[str | None], mode: str = "literal") -> str | None:
    """Root template of one column of texts in this process, for sheets that fit a task."""
    import re
    from collections import Counter

    from sheetgraph.functions import text as X

    counts = Counter(v for v in values if v)
    if not counts:
        return None
    delimiter, integer = re.compile(r"[^\w\s]+|_+"), re.compile(X.INT)
    bits = (("int", X.INT), ("point", X.DECIMAL_POINT), ("comma", X.DECIMAL_COMMA))

    def mask(v: str) -> int:
        parts = [p.strip() for p in delimiter.split(v) if p.strip()]
        words = re.split(r"[\W_]+", v.lower().strip())
        yes, no = (sum(w in of for w in words) for of in (X.TRUE_WORDS, X.FALSE_WORDS))
        out = sum(BITS[b] for b, pattern in bits if re.match(pattern, v))
        return out + BITS["list"] * bool(parts and all(map(integer.match, parts))) + BITS["word"] * (yes != no)

    classes_, tokens = {}, Counter()
    for v, n in counts.items():
        m = mask(v)
        x = classes_.setdefault(m, {"kind": "S", "format_class": None, "mask": m, "cells": 0, "singles": 0, "texts": 0, "length": 0})
        x["cells"], x["singles"], x["texts"], x["length"] = x["cells"] + n, x["singles"] + (n == 1), x["texts"] + 1, x["length"] + n * len(v)
        for p in delimiter.split(v):
            if p.strip():
                tokens[p.strip(), m] += n
    spread: dict[str, list] = {}
    for (p, m), n in tokens.items():
        spread.setdefault(p, []).append({"mask": m, "times": min(n, 2)})
    totals = {m: {"mask": m, "t": 0, "t_int": 0} for m in classes_}
    for (p, m), n in tokens.items():
        totals[m]["t"] += n
        totals[m]["t_int"] += n * bool(integer.match(p))
    nodes = grow(list(classes_.values()), [{"pattern": at, "tokens": 1} for at in spread.values()], list(totals.values()), mode)
    return nodes[0][1] if nodes else None


def evidence(values: DataFrame) -> DataFrame:
    """A row for each column: its classes, token patterns and token counts as arrays, from its value dictionary."""
    tokens = token_dictionary(values)
    of = classes(values).groupBy(*COLUMN).agg(F.collect_list(F.struct("kind", "format_class", "mask", "cells", "singles", "texts", "length")).alias("classes"))
    patterns = token_patterns(tokens).groupBy(*COLUMN).agg(F.collect_list(F.struct("pattern", "is_int", "tokens", "cnt")).alias("patterns"))
    counts = token_counts(tokens).groupBy(*COLUMN).agg(F.collect_list(F.struct("mask", "t", "t_int")).alias("counts"))

    def same(a: DataFrame, b: DataFrame):
        x = [a[k].eqNullSafe(b[k]) for k in COLUMN]
        return x[0] & x[1] & x[2]

    got = of.join(patterns, same(of, patterns), "left").select(*[of[k] for k in of.columns], "patterns")
    return got.join(counts, same(got, counts), "left").select(*[got[k] for k in got.columns], "counts")


def build(cells: DataFrame, mode: str = "literal", templates: tuple[str, ...] | None = None, max_depth: int = 15, hints: DataFrame | None = None) -> DataFrame:
    """The tree of each column as rows, by level. hints: sheet_id, col, template that an expert wants first."""
    return build_from(value_dictionary(cells), mode, templates, max_depth, hints)


def build_from(values: DataFrame, mode: str = "literal", templates: tuple[str, ...] | None = None, max_depth: int = 15, hints: DataFrame | None = None, choices: dict[str, tuple[str, ...]] | None = None) -> DataFrame:
    """The trees from a value dictionary, which may be a stored one: its scan is then the only one over the cells.

    choices: templates of several trees for each column, by the end that the names of their sheets get.
    """
    rows = evidence(values)
    rows = rows.withColumn("hint", F.lit(None).cast("string")) if hints is None else rows.join(hints.select("sheet_id", "col", F.col("template").alias("hint")), ["sheet_id", "col"], "left").select(*rows.columns, "hint")
    several = {end: set(ts) for end, ts in choices.items()} if choices else {"": set(templates) if templates else None}
    more = dict(REGISTERED)
    prepare(values.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for r in batch.to_pylist():
                for end, allowed in several.items():
                    for node in grow(r["classes"], r["patterns"] or [], r["counts"] or [], mode, allowed, max_depth, r["hint"], more):
                        out.append((r["sheet_id"] + end, r["col"], r["style_key"], *node))
            kinds = (pa.string(), pa.string(), pa.string(), pa.int32(), pa.string(), pa.float64(), pa.int32(), pa.int64(), pa.bool_())
            cols = list(zip(*out)) if out else [()] * 9
            names = [x.split()[0] for x in NODES.split(", ")]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], names=names)

    return rows.mapInArrow(run, NODES)
