"""Grading in the row: the same counts as statements matched cell by cell, and no shuffle of statements."""

from functools import partial

from sheetgraph.operators import baseline, match, tree
from sheetgraph.operators import cells as C
from sheetgraph.plans import in_row, mess, truth, workloads
from sheetgraph.queries import QUERIES


def _rows(df):
    return sorted((r.graph, r.pattern, r.tp, r.fp, r.fn) for r in df.collect())


def test_styled_runs_equal_the_general_way(spark, sf):
    patterns, graphs = ("value_as_color", "all"), ("K3",)
    cells, goal = workloads.messy_runs(spark, sf, patterns, graphs)
    general = workloads.grade_runs(workloads.predict(cells), goal)
    assert _rows(workloads._predicted_runs(workloads._messy_sheets(spark, sf, patterns, graphs))) == _rows(general)


def test_unchanged_columns_are_counted_once(spark, sf):
    _, clean = in_row.read(spark, sf, "events")
    change = partial(mess.in_row, "value_as_color")
    assert [c.col for c in clean if change(c) is not c] == ["event_type"]


def test_repeated_row_names_go_the_general_way(spark, tmp_path):
    spark.createDataFrame([(1, "a"), (1, "a")], "r_regionkey int, r_name string").write.parquet(str(tmp_path / "region.parquet"))
    assert not in_row.possible(spark, str(tmp_path), ("region",))
    (got,) = workloads.grade_expected(spark, str(tmp_path), ("region",)).collect()
    assert (got.tp, got.fp, got.fn) == (2, 0, 0)  # two equal rows are one graph


def test_recursion_reads_line_items(spark, sf):
    got = {r.n: r["items"] for r in QUERIES["cte_recursive"](spark, sf).collect()}
    assert sorted(got) == list(range(1, 21)) and sum(got.values()) == spark.read.parquet(f"{sf}/lineitem.parquet").count()


def test_numbers_are_counted_by_sums_and_read_texts_once(spark, sf):
    (sheet,) = in_row.plain_sheets(spark, sf, ("customer",))
    got = {(r.col, r.mask): r.cnt for r in in_row._numbers(sheet).collect()}
    assert got[("c_custkey", 128)] == got[("c_acctbal", 128)] + got[("c_acctbal", 256)] == sheet.df.count()
    names = [c.col for c in sheet.seen]
    parts = in_row._by_text(sheet, {("customer", c): {None: [("T11", False)]} for c in names})
    assert [(len(x.seen), "w" in x.df.columns) for x in parts] == [(1, True), (1, True), (3, False)]
    assert parts[1].df.count() == 5  # c_mktsegment's different texts


def test_odd_numbers_and_texts_as_in_the_general_way(spark, tmp_path):
    odd = [float("nan"), None, float("inf"), 1e-13, 1e26, 1e15, 3.0, -0.5]
    rows = [(k if k else None, name, k, x) for k, (name, x) in enumerate(zip(["<b>x</b>", "", None, "http://a", "12", "s_name", "<i></i>", "a\n"], odd))]
    spark.createDataFrame(rows, "s_suppkey long, s_name string, s_nationkey int, s_acctbal double").write.parquet(str(tmp_path / "supplier.parquet"))
    d, of = str(tmp_path), ("supplier",)
    cells = C.portal_cells(spark, d, of)
    goal = truth.expected(spark, cells, of)
    for how in ("display", "raw"):
        assert workloads.grade_baseline(spark, d, how, of).collect() == match.grade(baseline.extract(cells, how), goal).collect()
    assert workloads.grade_portal(spark, d, "literal", of).collect() == match.grade(workloads.predict(cells, split=False), goal).collect()


def test_runs_share_the_columns_they_see_alike(spark, sf):
    patterns = ("clean", "value_as_color", "outdated_struck")
    events, labels = workloads._messy_sheets(spark, sf, patterns, ("K3",), ends=("|true", "|false"), flat=("|false",))
    # each plain column once; the event's type once more for each pattern that styles it, with its styles and without
    assert (len(events.seen), len(labels.seen)) == (6 + 4, 3)
    assert {len(runs) for _, c, _, runs in events.cells() if c.col != "event_type"} == {6}
    assert sorted(len(runs) for _, c, _, runs in events.cells() if c.col == "event_type") == [1, 1, 1, 1, 2]


def test_shared_runs_without_styles_equal_the_general_way(spark, sf):
    patterns, graphs = ("value_as_color", "clean"), ("K3",)
    cells, goal = workloads.messy_runs(spark, sf, patterns, graphs)
    general = workloads.grade_runs(workloads.predict(cells, split=False), goal)
    sheets = workloads._messy_sheets(spark, sf, patterns, graphs, ends=("|true", "|false"), flat=("|false",))
    got = workloads._predicted_runs(sheets, more=("split",))
    assert _rows(got.where("split = 'false'")) == _rows(general)


def test_trees_of_several_choices_are_those_of_each(spark, sf):
    values = in_row.dictionary(in_row.plain_sheets(spark, sf, ("customer",)), set())
    without = {"|a": ("T9", "T13", "T14"), "|b": ("T10", "T13", "T14")}
    both = {tuple(r) for r in tree.build_from(values, choices=without).collect()}
    each = {(r[0] + end, *r[1:]) for end, ts in without.items() for r in tree.build_from(values, templates=ts).collect()}
    assert both == each and len(both) > 8


def test_numbers_that_become_texts_are_made_once_a_number(spark, sf):
    patterns, graphs = ("numbers_as_text", "clean"), ("K3",)
    sheets = workloads._messy_sheets(spark, sf, patterns, graphs)
    (value,) = [x for x in sheets if "w" in x.df.columns]
    assert [c.col for c in value.seen] == ["value"] and value.names == ("K3|numbers_as_text|events",)
    events = spark.read.parquet(f"{sf}/events.parquet")
    assert (value.df.count(), value.df.agg({"w": "sum"}).first()[0]) == (events.select("value").distinct().count(), events.count())
    cells, goal = workloads.messy_runs(spark, sf, patterns, graphs)
    general = workloads.grade_runs(workloads.predict(cells, "literal"), goal)
    assert _rows(workloads._predicted_runs(sheets)) == _rows(general)
