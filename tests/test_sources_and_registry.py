"""Workbooks, the funnel, registered templates, and that every covered cell yields a statement."""

import random

import pytest
from pyspark.sql import functions as F

from sheetgraph.functions import text as X
from sheetgraph.operators import execute, heuristics, linking, match, richtext, tree
from sheetgraph.plans import workloads
from sheetgraph.sources import workbook
from tests.test_core import GOLDEN, SCHEMA, column


def test_workbook_cells_keep_formats_and_styles():
    content = workbook.write({"a": [["k", "day", "flag", "text", "rich"], [1, (44228.5, "dd.mm.yyyy hh:mm"), (1, '"Yes";;"No"'), "x & <y", 'old <strike>a</strike> <font color="#ff0000"><b>b</b></font>'], [2.5, (44228, "yyyy-mm-dd"), True, None, "plain"]]})
    rows = {(r[1], r[2]): r for r in workbook.read("f.xlsx", content)}
    assert rows["2", "day"][6] == 44228.5 and rows["2", "day"][8] == "datetime" and rows["3", "day"][8] == "date"
    assert rows["2", "flag"][7] is True and rows["3", "flag"][4] == "B" and ("3", "text") not in rows
    assert rows["2", "text"][5] == "x & <y" and rows["2", "text"][9] is None
    assert rows["2", "rich"][9] == 'old <strike>a</strike> <font color="#ff0000"><b>b</b></font>' and rows["2", "rich"][5] == "old a b"
    with pytest.raises(workbook.Unreadable):
        list(workbook.read("f.xlsx", content[: len(content) // 2]))


def test_funnel(spark, sf):
    assert tuple(workloads.collection_funnel(spark, sf).first()) == (6, 5, 3, 2)


def test_every_covered_cell_yields_a_statement(spark):
    rows = [r for cells, _ in GOLDEN.values() for r in cells]
    rows += column("x1", 1, 2, 3, "q", "q") + column("x2", "---", "a b", "---", "a b", "a b") + column("x3", "Köln", "köln", "北京", "東京", "北京", "東京") + column("x4", 1e30, 2.0)
    random.seed(6)
    pool = ["yes", "no", "q", "1", "2.5", "3,5", "2021-02-01", "3. März 2021", "4; 5", "red; blue", 1, 2.5, True, (44228, "date"), "..."]
    for k in range(40):
        rows += column(f"r{k}", *[random.choice(pool) for _ in range(random.randint(1, 9))])
    cells = spark.createDataFrame(rows, SCHEMA)
    for mode in heuristics.MODES:
        nodes = tree.build(cells, mode).collect()
        made = execute.run(execute.generate(spark.createDataFrame(nodes, tree.NODES)), cells, mode)
        covered = {}
        for n in nodes:
            covered[n.sheet_id] = covered.get(n.sheet_id, 0) + n.cells
        got = {r.sheet_id: r["count"] for r in made.select("sheet_id", "row_id").distinct().groupBy("sheet_id").count().collect()}
        assert got == covered, mode


def test_labels_stay_apart_and_iris_are_encoded(spark):
    labels = ["北京", "東京", "Köln", "a b", "a-b", "-"]
    got = spark.createDataFrame([(x,) for x in labels], "x string").select(X.entity_iri(F.col("x")).alias("i")).collect()
    assert len({r.i for r in got}) == len(labels) and all(r.i.isascii() for r in got)


def test_serials_need_no_time_zone(spark):
    zone = spark.conf.get("spark.sql.session.timeZone")
    try:
        for z in ("America/New_York", "Asia/Kolkata", "UTC"):
            spark.conf.set("spark.sql.session.timeZone", z)
            ntz = F.lit("2021-03-14 02:30:00").cast("timestamp_ntz")
            r = spark.range(1).select(X.serial_datetime(F.lit(44228.3479166667)).alias("a"), X.serial_datetime(X.serial_of(ntz)).alias("b"), X.date_text(F.lit("14.3.2021")).alias("c")).first()
            assert tuple(r) == ("2021-02-01T08:21:00", "2021-03-14T02:30:00", "2021-03-14")
    finally:
        spark.conf.set("spark.sql.session.timeZone", zone)


def test_registered_template(spark):
    code = heuristics.Template("X1", "code", 9, "value", "literal", "xsd:token", "", 30)
    entry = heuristics.Registered(code, lambda live: float(all(x["kind"] == "S" for x in live)), lambda kind, fmt, mask: kind == "S", lambda: F.col("kind") == "S", lambda: F.array(F.upper("s")))
    heuristics.register(entry)
    try:
        with pytest.raises(ValueError):
            heuristics.register(entry)
        cells = spark.createDataFrame(column("s", "ab", "cd", "ef"), SCHEMA)
        nodes = tree.build(cells)
        assert [r.template for r in nodes.collect()] == ["X1"]
        assert {(r.o, r.o_datatype) for r in execute.run(execute.generate(nodes), cells).collect()} == {("AB", "xsd:token"), ("CD", "xsd:token"), ("EF", "xsd:token")}
    finally:
        heuristics.REGISTERED.clear()


def test_matching_is_exact_where_resources_have_two_predicates():
    random.seed(8)
    for _ in range(200):
        graphs = [list({(f"{side}p{random.randint(1, 3)}", f"{side}e{random.randint(1, 3)}", "iri", "") for _ in range(random.randint(1, 4))}) for side in "ab"]
        assert match.best_overlap(*graphs) == match.brute_force(*graphs)


def test_labels_of_many_words_are_linked(spark):
    texts = spark.createDataFrame([(1, "the seven words of this very long label are here")], "id long, text string")
    lexicon = spark.createDataFrame([("seven words of this very long label",)], "label string")
    assert linking.link_ngrams(texts, lexicon, "id", "text").count() == 1
    with pytest.raises(ValueError):
        linking.link_automaton(texts, lexicon, "id", "text", max_labels=0)


def test_styled_functions_are_in_the_printed_mapping(spark):
    rows = [("s", "1", "c", None, "S", t, None, None, None, t) for t in ("<b>x</b> y", '<font color="#ff0000">z</font>')]
    cells = richtext.split(spark.createDataFrame(rows, SCHEMA))
    lines = " ".join(r.line for r in execute.turtle_lines(execute.generate(tree.build(cells))).collect())
    assert all(x in lines for x in ('getEntitiesByTag"; fn:tag "b"', 'getEntitiesByColor"; fn:color "#ff0000"', "getEntitiesByUnformatted", "#%23ff0000>"))


def test_hints_come_first(spark):
    cells = spark.createDataFrame(column("s", "y", "n", "y", "n"), SCHEMA)
    hints = spark.createDataFrame([("s", "c", "T11")], "sheet_id string, col string, template string")
    assert [r.template for r in tree.build(cells).collect()] == ["T8"]
    assert tree.build(cells, hints=hints).where("level = 0").first().template == "T11"
