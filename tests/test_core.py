"""Worked examples, golden columns and invariants of the mapping predictor."""

import random

import pytest
from pyspark.sql import functions as F

from sheetgraph import queries
from sheetgraph.functions import text as X
from sheetgraph.operators import cells as C
from sheetgraph.operators import execute, heuristics, linking, match, profile, richtext, tree
from sheetgraph.plans import truth, workloads

DUP = {"aaaaaa": 1.00, "aaabbb": 0.92, "aaaabb": 0.92, "aabbcc": 0.83, "aaabbc": 0.75, "aaabbbcd": 0.69, "aabbbcd": 0.64, "aabbcd": 0.58, "aaaabcde": 0.50, "aaabcd": 0.50, "aabc": 0.50, "aaacdef": 0.43, "aacdef": 0.33, "abcdef": 0.08}


def column(name, *values, fmt=None):
    """Cells of one column: text, numbers, booleans; fmt for the numbers, or by value as (number, fmt)."""
    rows = []
    for k, v in enumerate(values):
        f = fmt
        if isinstance(v, tuple):
            v, f = v
        kind = "B" if isinstance(v, bool) else "S" if isinstance(v, str) else "N"
        rows.append((name, str(k), "c", None, kind, v if kind == "S" else None, float(v) if kind == "N" else None, v if kind == "B" else None, f if kind == "N" else None, None))
    return rows


SCHEMA = "sheet_id string, row_id string, col string, style_key string, kind string, s string, n double, b boolean, format_class string, rich string"
GOLDEN = {
    "g1": (column("g1", 0, 1, 2, 3, 4), [("T13", 1.0, 5)]),
    "g2": (column("g2", "2021-02-01", "3.2.2021", 44228, 44229, fmt="date"), [("T5", 1.0, 4)]),
    "g3": (column("g3", *range(9), "N/A"), [("T9", 0.95, 10)]),
    "g4": (column("g4", "yes", "no", "no", "yes"), [("T8", 1.0, 4)]),
    "g5": (column("g5", *["lung"] * 4), [("T11", 1.0, 4)]),
    "g6": (column("g6", "42, 15; 3", "7; 8"), [("T7", 1.0, 2)]),
    "g7": (column("g7", "1,5", "2,25", "3,0"), [("T4", 1.0, 3)]),
    "g8": (column("g8", *map(str, range(1, 7)), *["pending"] * 4), [("T2", 0.6, 6), ("T11", 1.0, 4)]),
    "g9": (column("g9", 1, 2, 2.5, 3.25), [("T6", 1.0, 4)]),
    "g10": (column("g10", True, False, True), [("T12", 1.0, 3)]),
    "g11": (column("g11", 44228, 44230, fmt="date"), [("T15", 1.0, 2)]),
    "g12": (column("g12", "y", "y", "y"), [("T8", 1.0, 3)]),
    "g14": (column("g14", "42", "7", "19"), [("T2", 1.0, 3)]),
    "g15": (column("g15", "red; blue", "blue; green", "green; red", "red"), [("T9", 0.875, 4)]),
    "g16": (column("g16", True), [("T12", 1.0, 1)]),
    "g17": (column("g17", (44228, "date"), (44229, "date"), (44230, "date"), 1, 2), [("T13", 1.0, 5)]),
    "g18": (column("g18", 1, 2, 3, True, False, *["alpha"] * 5), [("T11", 0.5, 5), ("T9", 0.9, 5)]),
}


def test_duplication_examples(spark, sf):
    got = {r.x: r.dup for r in queries.dup_of_letters(spark.createDataFrame([(x,) for x in DUP], "x string")).collect()}
    assert {k: round(v, 2) for k, v in got.items()} == DUP
    names = {r.c_name for r in spark.read.parquet(f"{sf}/customer.parquet").collect()}
    assert {r.x for r in queries.QUERIES["dup_examples"](spark, sf).collect()} == names


def test_golden_columns(spark):
    rows = [r for cells, _ in GOLDEN.values() for r in cells]
    nodes = tree.build(spark.createDataFrame(rows, SCHEMA)).collect()
    for name, (_, chain) in GOLDEN.items():
        got = [(r.template, round(r.score, 4), r.cells) for r in sorted((x for x in nodes if x.sheet_id == name), key=lambda x: x.level)]
        assert got == chain, name


def test_tree_root_is_the_pick(spark, sf):
    cells = C.portal_cells(spark, sf, ("part", "orders", "labels"))
    for mode in heuristics.MODES:
        roots = {(r.sheet_id, r.col): r.template for r in tree.build(cells, mode).where("level = 0").collect()}
        assert roots == {(r.sheet_id, r.col): r.template for r in heuristics.predict_roots(cells, mode).collect()}


def test_scores_stay_in_range(spark, sf):
    scored = heuristics.scores(profile.column_profile(C.portal_cells(spark, sf, ("part", "documents", "events"))))
    assert scored.where("score < 0 or score > 1").count() == 0
    t = scored.where("template in ('T9', 'T10')").groupBy("sheet_id", "col").agg(F.sum("score").alias("x"), F.count(F.lit(1)).alias("n"))
    assert t.where("x > 1.000001").count() == 0


def test_values_out_of_text(spark):
    row = spark.range(1).select(
        X.serial_datetime(F.lit(44228.3479166667)).alias("at"),
        X.date_text(F.lit("3. März 2021")).alias("d1"),
        X.date_text(F.lit("March 3, 2021")).alias("d2"),
        X.date_text(F.lit("30.2.2021")).alias("d3"),
        X.datetime_text(F.lit("02/01/2021 08:21 PM")).alias("t"),
        X.parse_number(F.lit("costs 1,50 each"), ",").alias("n"),
        X.decimal_places(F.lit(0.023)).alias("dp"),
        X.parse_boolean(F.lit("yes no")).alias("tie"),
        X.tokens(F.lit("DB; IR (42)")).alias("tokens"),
    ).first()
    assert (row.at, row.d1, row.d2, row.d3, row.t, row.n, row.dp, row.tie, row.tokens) == ("2021-02-01T08:21:00", "2021-03-03", "2021-03-03", None, "2021-02-01T20:21:00", "1.5", 3, None, ["DB", "IR", "42"])


@pytest.mark.parametrize("rich, want", [("a <b>b</b> c", {"": "a c", "b": "b"}), ('<font color="#ff0000"><b>x</b></font>', {"b+#ff0000": "x"}), ("<i>a<u>b</u></i>", {"i": "a", "i+u": "b"}), ("<p><b>t<br><p>u", {"b": "t u"}), ('<font color="#000000">k</font> &amp;', {"": "k &"})])
def test_styles(spark, rich, want):
    rows = spark.createDataFrame([("s", "1", "c", None, "S", rich, None, None, None, rich), ("s", "2", "c", None, "S", "<b>z</b>", None, None, None, "<b>z</b>")], SCHEMA)
    assert {r.style_key: r.s for r in richtext.split(rows).where("row_id = '1'").collect()} == want


def test_matchers_agree_with_brute_force():
    random.seed(1)
    for _ in range(300):
        graphs = [list({(f"{side}p{random.randint(1, 2)}", *((f"{side}e{random.randint(1, 3)}", "iri", "") if random.random() < 0.5 else (str(random.randint(1, 3)), "literal", "xsd:integer"))) for _ in range(random.randint(0, 4))}) for side in "ab"]
        best = match.brute_force(*graphs)
        assert best == match.greedy(*graphs)[0] == match.greedy(*graphs, literal_first=False)[0]


def test_matching_fixtures(spark):
    lit, iri, base = "literal", "iri", ("sheet", "r")
    cells = {
        "m1": ([("p1", "Ann", lit), ("p2", "e1", iri)], [("q1", "Ann", lit), ("q2", "E9", iri)], (2, 0, 0)),
        "m2": ([("p1", "1", lit), ("p1", "2", lit)], [("q1", "1", lit), ("q1", "3", lit)], (1, 1, 1)),
        "m3": ([("p1", "e1", iri), ("p2", "e1", iri)], [("q1", "E1", iri), ("q1", "E2", iri)], (1, 1, 1)),
        "m4": ([], [("q1", "1", lit), ("q2", "2", lit)], (0, 0, 2)),
        "m6": ([("p", "x", iri), ("p", "y", iri)], [("p", "y", iri), ("p", "z", iri)], (2, 0, 0)),
    }

    def side(k):
        rows = [(*base, name, "s", p, o, kind, None) for name, x in cells.items() for p, o, kind in x[k]]
        return spark.createDataFrame(rows, "sheet_id string, row_id string, col string, s string, p string, o string, o_kind string, o_datatype string")

    for method in ("auto", "greedy"):
        got = {r.col: (r.tp, r.fp, r.fn) for r in match.match_cells(side(0), side(1), method).collect()}
        assert got == {k: v[2] for k, v in cells.items()}


def test_expected_mapping_grades_one(spark, sf):
    assert {r.f for r in workloads.grade_expected(spark, sf, ("nation", "labels", "orders")).collect()} == {1.0}
    assert {r.f for r in workloads.renamed_recovers(spark, sf, ("nation", "customer")).collect()} == {1.0}


def test_predictor_beats_the_baseline(spark, sf):
    sheets = ("customer", "orders", "labels")
    ours = {r.sheet_id: r.f for r in workloads.grade_portal(spark, sf, "literal", sheets).collect()}
    flat = {r.sheet_id: r.f for r in workloads.grade_baseline(spark, sf, "display", sheets).collect()}
    assert all(ours[s] > flat[s] for s in sheets)


def test_linking(spark):
    texts = spark.createDataFrame([(1, "the Red Ring"), (2, "credit"), (3, None)], "id long, text string")
    lexicon = spark.createDataFrame([("red",), ("red ring",), ("ring",)], "label string")
    longest = linking.link_automaton(texts, lexicon, "id", "text").collect()
    assert [(r.id, r.label) for r in longest] == [(1, "red ring")]
    assert {r.label for r in linking.link_automaton(texts, lexicon, "id", "text", "all").collect()} == {"red", "red ring", "ring"}
    assert {r.label for r in linking.link_ngrams(texts, lexicon, "id", "text").collect()} == {"red", "red ring", "ring"}


def test_ntriples_and_turtle(spark, sf):
    cells = C.portal_cells(spark, sf, ("nation",))
    mapping = truth.expected_mapping(spark, ("nation",))
    assert execute.ntriples(execute.run(mapping, cells)).where("line not rlike ' \\\\.$'").count() == 0
    assert execute.turtle_lines(mapping).count() == 3


def test_entry():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())
