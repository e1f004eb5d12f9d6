"""Registered queries of the methods and the engine surface, each with the SQL that must agree where SQL can."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sheetgraph import surface
from sheetgraph.functions import text as X
from sheetgraph.operators import cells as C
from sheetgraph.operators import execute, heuristics, profile, richtext, tree
from sheetgraph.plans import mess, truth, workloads

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLE[name] = sql
        return f

    return add


def table(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


# ---- degree of duplication

DUP_SQL = "CASE WHEN c <= 1 THEN 0.0 ELSE round((2.0*c - u - p + 1) / (2.0*c), 6) END"


@query("dup_examples", "WITH l AS (SELECT c_name AS x, unnest(string_split(c_name, '')) AS v FROM customer), g AS (SELECT x, v, count(*) AS n FROM l WHERE v <> '' GROUP BY x, v), s AS (SELECT x, sum(n) AS c, sum(CASE WHEN n = 1 THEN 1 ELSE 0 END) AS u, count(*) AS p FROM g GROUP BY x) SELECT x, " + DUP_SQL + " AS dup FROM s")
def dup_examples(spark, d):
    """Multisets of letters, one for each customer's name."""
    return dup_of_letters(table(spark, d, "customer").select(F.col("c_name").alias("x")))


def dup_of_letters(texts: DataFrame) -> DataFrame:
    """The degree of each text's letters; x: the texts."""
    rows = texts.select("x", F.explode(F.split("x", "")).alias("v")).where("v != ''")
    g = rows.groupBy("x", "v").agg(F.count(F.lit(1)).alias("n")).groupBy("x").agg(F.sum("n").alias("c"), F.count_if(F.col("n") == 1).alias("u"), F.count(F.lit(1)).alias("p"))
    return g.select("x", F.round(heuristics.dup(F.col("c"), F.col("u"), F.col("p")), 6).alias("dup"))


def _dup(name: str, tab: str, col: str) -> None:
    sql = f"WITH g AS (SELECT {col}, count(*) AS n FROM {tab} WHERE {col} IS NOT NULL AND {col} <> '' GROUP BY 1), s AS (SELECT CAST(sum(n) AS BIGINT) AS c, count_if(n = 1)::BIGINT AS u, count(*) AS p FROM g) SELECT c, u, p, {DUP_SQL} AS dup FROM s"
    query(name, sql)(lambda spark, d: heuristics.dup_degree(table(spark, d, tab), col))


for _n, _t, _c in (("dup_part_brand", "part", "p_brand"), ("dup_orders_priority", "orders", "o_orderpriority"), ("dup_customer_segment", "customer", "c_mktsegment"), ("dup_lineitem_status", "lineitem", "l_linestatus"), ("dup_documents_lang", "documents", "lang"), ("dup_documents_text", "documents", "text"), ("dup_events_type", "events", "event_type"), ("dup_nation_name", "nation", "n_name")):
    _dup(_n, _t, _c)

# ---- scores of the templates, on sheets with text and numbers

TEXT = {"part": ("p_name", "p_brand", "p_type"), "orders": ("o_orderstatus", "o_orderpriority"), "customer": ("c_name", "c_mktsegment"), "events": ("event_type", "props"), "nation": ("n_name",)}
NUMBERS = {"part": ("p_partkey", "p_size", "p_retailprice"), "orders": ("o_orderkey", "o_custkey", "o_totalprice"), "customer": ("c_custkey", "c_nationkey", "c_acctbal"), "events": ("event_id", "user_id", "value"), "nation": ("n_nationkey", "n_regionkey")}


def _scores_sql(tab: str) -> str:
    parts = []
    for col in TEXT[tab]:
        parts.append(f"""
SELECT '{col}' AS col, unnest(['T2','T3','T4','T7','T8','T9','T10','T11']) AS template, round(unnest([ints/c, points/c, commas/c, CASE WHEN t > 0 THEN ti/t ELSE 0 END, CASE WHEN p <= 2 AND len/c < 3.5 THEN 1.0 ELSE 0.0 END, 1 - dup, dup, CASE WHEN t <= 1 THEN 0.0 ELSE (2*t - ut - pt + 1) / (2*t) END]), 6) AS score FROM (
 SELECT *, CASE WHEN c <= 1 THEN 0.0 ELSE (2*c - u - p + 1) / (2*c) END AS dup FROM
 (SELECT sum(n)::DOUBLE AS c, count_if(n = 1)::DOUBLE AS u, count(*)::DOUBLE AS p, sum(n * length(v))::DOUBLE AS len, coalesce(sum(n) FILTER (regexp_full_match(v, '[+-]?[0-9]+')), 0)::DOUBLE AS ints, coalesce(sum(n) FILTER (regexp_full_match(v, '[+-]?[0-9]+[.][0-9]+')), 0)::DOUBLE AS points, coalesce(sum(n) FILTER (regexp_full_match(v, '[+-]?[0-9]+,[0-9]+')), 0)::DOUBLE AS commas FROM (SELECT {col} AS v, count(*) AS n FROM {tab} WHERE {col} <> '' GROUP BY 1)),
 (SELECT coalesce(sum(n), 0)::DOUBLE AS t, count_if(n = 1)::DOUBLE AS ut, count(*)::DOUBLE AS pt, coalesce(sum(n) FILTER (regexp_full_match(v, '[+-]?[0-9]+')), 0)::DOUBLE AS ti FROM (SELECT v, count(*) AS n FROM (SELECT regexp_replace(unnest(regexp_split_to_array({col}, '[^\\p{{L}}\\p{{N}}\\s]+')), '^\\s+|\\s+$', '', 'g') AS v FROM {tab} WHERE {col} <> '') WHERE v <> '' GROUP BY 1)))""")
    for col in NUMBERS[tab]:
        parts.append(f"SELECT '{col}' AS col, unnest(['T13','T14']) AS template, round(unnest([count_if({col} = floor({col}))::DOUBLE / count(*), count_if({col} <> floor({col}))::DOUBLE / count(*)]), 6) AS score FROM {tab}")
    return " UNION ALL ".join(parts)


def _scores(tab: str) -> None:
    @query(f"scores_{tab}", _scores_sql(tab))
    def run(spark, d):
        cells = C.from_table(C.read_sheet(spark, d, tab), C.SPECS[tab]).where(F.col("col").isin(*TEXT[tab], *NUMBERS[tab]))
        got = heuristics.scores(profile.column_profile(cells))
        text = F.col("col").isin(*TEXT[tab]) & F.col("template").isin("T2", "T3", "T4", "T7", "T8", "T9", "T10", "T11")
        number = F.col("col").isin(*NUMBERS[tab]) & F.col("template").isin("T13", "T14")
        return got.where(text | number).select("col", "template", F.round("score", 6).alias("score"))


for _t in TEXT:
    _scores(_t)


@query("scores_labels_bool", "SELECT unnest(['quality','toxic']) AS col, 1.0::DOUBLE AS score")
def scores_labels_bool(spark, d):
    cells = C.portal_cells(spark, d, ("labels",)).where("col != 'doc_id'")
    return heuristics.scores(profile.column_profile(cells)).where("template = 'T12'").select("col", "score")


@query("scores_dates", "SELECT 'o_orderdate' AS col, 'T15' AS template, 1.0::DOUBLE AS score UNION ALL SELECT 'l_shipdate', 'T15', 1.0 UNION ALL SELECT 'ts', 'T15t', 1.0")
def scores_dates(spark, d):
    cells = C.portal_cells(spark, d, ("orders", "lineitem", "events")).where(F.col("col").isin("o_orderdate", "l_shipdate", "ts"))
    return heuristics.pick(heuristics.scores(profile.column_profile(cells))).select("col", "template", "score")


for _mode in heuristics.MODES:
    query(f"pick_all_tables_{_mode}")(lambda spark, d, m=_mode: heuristics.predict_roots(C.portal_cells(spark, d), m).drop("style_key"))
    query(f"grade_portal_{_mode}")(lambda spark, d, m=_mode: workloads.grade_portal(spark, d, m))
query("trees_all_tables")(lambda spark, d: tree.build(C.portal_cells(spark, d)).drop("style_key"))
query("tree_numbers_and_words")(lambda spark, d: workloads.numbers_with_words(spark, d).drop("style_key"))
query("error_confusion")(workloads.error_confusion)

# ---- cells and parsing


@query("cell_kinds", "SELECT 'customer' AS sheet_id, kind, n FROM (SELECT 'N' AS kind, CAST(count(c_custkey) + count(c_nationkey) + count(c_acctbal) AS BIGINT) AS n FROM customer UNION ALL SELECT 'S', CAST(count(c_name) + count(c_mktsegment) AS BIGINT) FROM customer) UNION ALL SELECT 'labels', kind, n FROM (SELECT 'N' AS kind, count(*) AS n FROM labels UNION ALL SELECT 'B', 2 * count(*) FROM labels)")
def cell_kinds(spark, d):
    return C.portal_cells(spark, d, ("customer", "labels")).groupBy("sheet_id", "kind").agg(F.count(F.lit(1)).alias("n"))


@query("decimal_places", "SELECT CASE WHEN l_extendedprice = round(l_extendedprice, 0) THEN 0 WHEN l_extendedprice = round(l_extendedprice, 1) THEN 1 ELSE 2 END AS places, count(*) AS n FROM lineitem GROUP BY 1")
def decimal_places(spark, d):
    return table(spark, d, "lineitem").select(X.decimal_places(F.col("l_extendedprice")).cast("int").alias("places")).groupBy("places").agg(F.count(F.lit(1)).alias("n"))


@query("parse_dates_three_forms", "SELECT o_orderkey, strftime(o_orderdate, '%Y-%m-%d') AS a, strftime(o_orderdate, '%Y-%m-%d') AS b, strftime(o_orderdate, '%Y-%m-%d') AS c, strftime(o_orderdate, '%Y-%m-%d') AS e FROM orders")
def parse_dates_three_forms(spark, d):
    day = F.col("o_orderdate")
    forms = {"a": "yyyy-MM-dd", "b": "M/d/yyyy", "c": "d.M.yyyy", "e": "MMMM d, yyyy"}
    return table(spark, d, "orders").select("o_orderkey", *[X.date_text(F.date_format(day, f)).alias(k) for k, f in forms.items()])


@query("serial_to_date", "SELECT l_orderkey, l_linenumber, strftime(l_shipdate, '%Y-%m-%d') AS day FROM lineitem")
def serial_to_date(spark, d):
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", X.serial_date(X.serial_of(F.col("l_shipdate"))).alias("day"))


@query("serial_to_datetime", "SELECT event_id, strftime(ts, '%Y-%m-%dT%H:%M:%S') AS at FROM events")
def serial_to_datetime(spark, d):
    return table(spark, d, "events").select("event_id", X.serial_datetime(X.serial_of(F.date_trunc("second", "ts"))).alias("at"))


@query("parse_comma_decimals", "SELECT o_orderkey, CAST(o_totalprice AS DECIMAL(38,2))::DOUBLE AS price FROM orders")
def parse_comma_decimals(spark, d):
    text = F.replace(X.decimal_text(F.col("o_totalprice")), F.lit("."), F.lit(","))
    return table(spark, d, "orders").select("o_orderkey", X.parse_number(text, ",").cast("double").alias("price"))


@query("separate_tokens", "SELECT token, count(*) AS n FROM (SELECT regexp_replace(unnest(regexp_split_to_array(p_brand, '[^\\p{L}\\p{N}\\s]+')), '^\\s+|\\s+$', '', 'g') AS token FROM part) WHERE token <> '' GROUP BY 1")
def separate_tokens(spark, d):
    return table(spark, d, "part").select(F.explode(X.tokens(F.col("p_brand"))).alias("token")).groupBy("token").agg(F.count(F.lit(1)).alias("n"))


@query("boolean_votes", "SELECT quality, count(*) AS n, CAST(count_if(quality = 1) AS BIGINT) AS yes FROM labels GROUP BY 1")
def boolean_votes(spark, d):
    word = F.when(F.col("quality") == 1, "Ja").otherwise("nein")
    return table(spark, d, "labels").select("quality", X.parse_boolean(word).alias("b")).groupBy("quality").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("b")).alias("yes"))


@query("styled_text", "SELECT o_orderkey, o_orderpriority AS bold, o_orderstatus AS red, 'plain' AS rest FROM orders")
def styled_text(spark, d):
    rich = F.concat(F.lit("plain <b>"), "o_orderpriority", F.lit('</b><font color="#FF0000">'), "o_orderstatus", F.lit("</font>"))
    return table(spark, d, "orders").select("o_orderkey", richtext.styled_by_tag(rich, "b").alias("bold"), richtext.styled_by_color(rich, "#ff0000").alias("red"), richtext.unstyled(rich).alias("rest"))


query("html_bold_pages")(lambda spark, d: table(spark, d, "pages").select("page_id", F.size(richtext.runs(F.col("html"))).alias("runs"), F.length(richtext.styled_by_tag(F.col("html"), "b")).alias("bold")))

# ---- mappings, statements, entities


@query("triples_nation", "SELECT 'urn:sheetgraph:nation/row/' || n_nationkey AS s, 'urn:sheetgraph:nation/prop/' || p AS p, o, dt AS o_datatype FROM (SELECT n_nationkey, 'n_nationkey' AS p, CAST(n_nationkey AS VARCHAR) AS o, 'xsd:integer' AS dt FROM nation UNION ALL SELECT n_nationkey, 'n_name', n_name, 'xsd:string' FROM nation UNION ALL SELECT n_nationkey, 'n_regionkey', CAST(n_regionkey AS VARCHAR), 'xsd:integer' FROM nation)")
def triples_nation(spark, d):
    cells = C.portal_cells(spark, d, ("nation",))
    return execute.run(execute.generate(tree.build(cells)), cells).select("s", "p", "o", "o_datatype")


@query("triples_orders", "SELECT row_id, col, o FROM (SELECT o_orderkey::VARCHAR AS row_id, unnest(['o_orderkey','o_custkey','o_orderdate','o_orderstatus','o_orderpriority']) AS col, unnest([o_orderkey::VARCHAR, o_custkey::VARCHAR, strftime(o_orderdate, '%Y-%m-%d'), 'urn:sheetgraph:entity/' || lower(o_orderstatus), 'urn:sheetgraph:entity/' || replace(lower(o_orderpriority), ' ', '%20')]) AS o FROM orders) UNION ALL SELECT o_orderkey::VARCHAR, 'o_totalprice', strftime(make_timestamp(((round(o_totalprice * 86400))::BIGINT - 25569 * 86400::BIGINT) * 1000000), '%Y-%m-%dT%H:%M:%S') FROM orders")
def triples_orders(spark, d):
    """The whole sheet; by the stated formulas a column of whole and fractional numbers reads as date-times."""
    cells = C.portal_cells(spark, d, ("orders",))
    return execute.run(execute.generate(tree.build(cells)), cells).select("row_id", "col", "o")


@query("triples_customer_calibrated", "SELECT row_id, col, o FROM (SELECT c_custkey::VARCHAR AS row_id, unnest(['c_custkey','c_name','c_nationkey','c_mktsegment']) AS col, unnest([c_custkey::VARCHAR, c_name, c_nationkey::VARCHAR, 'urn:sheetgraph:entity/' || lower(c_mktsegment)]) AS o FROM customer) UNION ALL SELECT c_custkey::VARCHAR, 'c_acctbal', CASE WHEN c_acctbal = round(c_acctbal) THEN CAST(c_acctbal::BIGINT AS VARCHAR) ELSE rtrim(CAST(c_acctbal::DECIMAL(38,2) AS VARCHAR), '0') END FROM customer")
def triples_customer_calibrated(spark, d):
    cells = C.portal_cells(spark, d, ("customer",))
    return execute.run(execute.generate(tree.build(cells, "calibrated")), cells, "calibrated").select("row_id", "col", "o")


query("mapping_turtle")(lambda spark, d: execute.turtle_lines(execute.generate(tree.build(C.portal_cells(spark, d, ("part", "orders"))))).drop("style_key"))


@query("entity_lexicon_part", "SELECT 'urn:sheetgraph:entity/' || lower(p_type) AS entity, min(p_type) AS label FROM part GROUP BY 1")
def entity_lexicon_part(spark, d):
    cells = C.portal_cells(spark, d, ("part",)).where("col = 'p_type'")
    return execute.lexicon(execute.generate(tree.build(cells)), cells)


@query("link_entities_ngram", "SELECT s.s_suppkey, n.n_name FROM supplier s JOIN nation n ON n.n_nationkey = s.s_nationkey")
def link_entities_ngram(spark, d):
    from sheetgraph.operators import linking

    s = table(spark, d, "supplier").join(F.broadcast(table(spark, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey"))
    texts = s.select("s_suppkey", F.concat(F.lit("maker of "), "n_name", F.lit(" goods")).alias("text"))
    lexicon = table(spark, d, "nation").select(F.col("n_name").alias("label"))
    return linking.link_ngrams(texts, lexicon, "s_suppkey", "text").select("s_suppkey", F.col("label").alias("n_name"))


# ---- experiments

query("grade_expected_mapping")(lambda spark, d: workloads.grade_expected(spark, d))
query("match_renamed_recovers")(lambda spark, d: workloads.renamed_recovers(spark, d))
for _how in ("display", "raw"):
    query(f"grade_baseline_{_how}")(lambda spark, d, h=_how: workloads.grade_baseline(spark, d, h))
for _name in ("all_strings", "native_only", "no_recursion"):
    query(f"ablation_{_name}")(lambda spark, d, n=_name: workloads.grade_ablation(spark, d, n))
for _p in mess.PATTERNS:
    query(f"grade_pattern_{_p}")(lambda spark, d, p=_p: workloads.grade_patterns(spark, d, "predictor", patterns=(p,)))
query("grade_patterns_baseline")(lambda spark, d: workloads.grade_patterns(spark, d, "display"))
query("grade_industry")(lambda spark, d: workloads.grade_industry(spark, d))
query("grade_industry_baseline")(lambda spark, d: workloads.grade_industry(spark, d, "display"))
query("manual_sheet_statements")(lambda spark, d: workloads.predict(mess.manual_sheet(spark, d)))
query("grade_orders_customer")(lambda spark, d: workloads.grade_portal(spark, d, "literal", ("orders", "customer")))

for _mode in heuristics.MODES:
    query(f"grade_portal_mean_{_mode}")(lambda spark, d, m=_mode: workloads.grade_portal_mean(spark, d, m))
query("grade_matchers")(lambda spark, d: workloads.grade_matchers(spark, d))
query("literal_first_visits")(lambda spark, d: workloads.literal_first_visits(spark, d))
query("ablation_entity_counts")(lambda spark, d: workloads.grade_entity_counts(spark, d))
query("ablation_no_style_split")(lambda spark, d: workloads.grade_without_styles(spark, d))
query("grade_patterns_baseline_raw")(lambda spark, d: workloads.grade_patterns(spark, d, "raw"))
query("grade_industry_baseline_raw")(lambda spark, d: workloads.grade_industry(spark, d, "raw"))
query("hinted_roots", "SELECT 'l_linestatus' AS col, 0 AS level, 'T11' AS template, count(l_linestatus) AS cells FROM lineitem UNION ALL SELECT 'l_returnflag', 0, 'T11', count(l_returnflag) FROM lineitem")(lambda spark, d: workloads.hinted_roots(spark, d))
query("collection_funnel", "SELECT count(*) AS listed, count_if(size > 0)::BIGINT AS fetched, count_if(size > 0 AND whole)::BIGINT AS parsed, count_if(size > 0 AND whole AND header)::BIGINT AS kept FROM (VALUES (9, true, true), (9, true, true), (4, false, true), (0, false, false), (9, false, false), (9, true, false)) t(size, whole, header)")(lambda spark, d: workloads.collection_funnel(spark, d))
query("workbook_cells", "SELECT 'world.xlsx/' || t AS sheet_id, col, kind, n, total, last FROM (SELECT 'nation' AS t, 'n_nationkey' AS col, 'N' AS kind, count(*) AS n, sum(n_nationkey)::DOUBLE AS total, NULL::VARCHAR AS last FROM nation UNION ALL SELECT 'nation', 'n_regionkey', 'N', count(*), sum(n_regionkey)::DOUBLE, NULL FROM nation UNION ALL SELECT 'nation', 'n_name', 'S', count(*), NULL, max(n_name) FROM nation UNION ALL SELECT 'region', 'r_regionkey', 'N', count(*), sum(r_regionkey)::DOUBLE, NULL FROM region UNION ALL SELECT 'region', 'r_name', 'S', count(*), NULL, max(r_name) FROM region)")(lambda spark, d: workloads.workbook_cells(spark, d))

# ---- engine surface: one SQL text for both engines

SQL_BOTH = {
    "join_inner": "SELECT c_mktsegment, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment",
    "join_left_counts": "SELECT lang, count(*) AS n, count(quality) AS labelled FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id GROUP BY lang",
    "join_semi": "SELECT count(*) AS n FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)",
    "join_anti": "SELECT count(*) AS n FROM customer c WHERE NOT EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey)",
    "agg_rollup": "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)",
    "agg_cube": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
    "agg_distinct": "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY l_returnflag",
    "agg_stats": "SELECT l_linestatus, round(stddev_pop(l_quantity), 6) AS sd, round(avg(l_discount), 6) AS mean FROM lineitem GROUP BY l_linestatus",
    "window_rank": "SELECT o_custkey, o_orderkey, CAST(row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS BIGINT) AS rn FROM orders",
    "window_running": "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS n FROM events",
    "set_intersect": "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier",
    "set_except": "SELECT n_nationkey AS k FROM nation EXCEPT SELECT s_nationkey FROM supplier",
    "dedup_texts": "SELECT count(*) AS n FROM (SELECT DISTINCT text FROM documents) t",
    "subquery_scalar": "SELECT count(*) AS n FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders)",
    "cte_recursive": "WITH RECURSIVE t(n) AS (SELECT min(l_linenumber) FROM lineitem UNION ALL SELECT n + 1 FROM t WHERE n < 20) SELECT n, count(l_linenumber) AS items FROM t LEFT JOIN lineitem ON l_linenumber = n GROUP BY n",
    "topk": "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25",
}
VIEWS = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "labels")


def _sql(spark: SparkSession, d: str, text: str) -> DataFrame:
    for v in VIEWS:
        if v in text:
            table(spark, d, v).createOrReplaceTempView(v)
    return spark.sql(text)


for _n, _s in SQL_BOTH.items():
    query(_n, _s)(lambda spark, d, s=_s: _sql(spark, d, s))


surface.register(query)


@query("join_asof_purchase", "SELECT event_id, coalesce(last_value(CASE WHEN event_type = 'click' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY event_id), -1) AS click FROM events")
def join_asof_purchase(spark, d):
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, 0)
    click = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)
    return table(spark, d, "events").select("event_id", F.coalesce(click, F.lit(-1).cast("long")).alias("click"))


@query("join_skew_salted", "SELECT l_returnflag, CAST(sum(o_custkey) AS BIGINT) AS s FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY l_returnflag")
def join_skew_salted(spark, d):
    joined = table(spark, d, "lineitem").join(table(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    part = joined.groupBy("l_returnflag", F.pmod("l_orderkey", F.lit(16)).alias("salt")).agg(F.sum("o_custkey").alias("s"))
    return part.groupBy("l_returnflag").agg(F.sum("s").alias("s"))


@query("vector_cosine_topk", "SELECT vec_id, round(list_cosine_similarity(embedding::DOUBLE[], (SELECT embedding::DOUBLE[] FROM embeddings WHERE vec_id = 0)), 4) AS cosine FROM embeddings ORDER BY cosine DESC, vec_id LIMIT 10")
def vector_cosine_topk(spark, d):
    e = table(spark, d, "embeddings")
    probe = F.broadcast(e.where("vec_id = 0").select(F.col("embedding").alias("q")))  # one row

    def dot(a, b):
        return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y), F.lit(0.0), lambda s, x: s + x)

    cosine = dot("embedding", "q") / F.sqrt(dot("embedding", "embedding") * dot("q", "q"))
    return e.join(probe).select("vec_id", F.round(cosine, 4).alias("cosine")).orderBy(F.desc("cosine"), "vec_id").limit(10)


@query("stream_tumbling", "SELECT date_trunc('day', ts) AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(spark, d):
    from sheetgraph.streaming import counts

    return counts.daily_counts(spark, d)


@query("stream_column_profile", f"WITH g AS (SELECT event_type, count(*) AS n FROM events GROUP BY 1), s AS (SELECT CAST(sum(n) AS BIGINT) AS c, count_if(n = 1)::BIGINT AS u, count(*) AS p FROM g) SELECT c, u, p, {DUP_SQL} AS dup FROM s")
def stream_column_profile(spark, d):
    from sheetgraph.streaming import counts

    return counts.running_dup(spark, d, "event_type")


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Predict, run and grade the orders sheet: one row for each column."""
    from sheetgraph.operators import match

    cells = C.portal_cells(spark, d, ("orders",))
    nodes = tree.build(cells)
    graded = match.grade(execute.run(execute.generate(nodes), cells), truth.expected(spark, cells, ("orders",)), by=("col",))
    return nodes.where("level = 0").select("col", "template", "score").join(graded, "col")


query("orders_end_to_end")(flagship)
