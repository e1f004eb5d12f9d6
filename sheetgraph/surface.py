"""The engine's general operators, one query each, on the given tables, with the SQL that must agree.

Where a DataFrame form has something to choose (a join strategy, a frame, a sketch) it is built here; plain
relational forms run one SQL text on both engines.
"""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sheetgraph.plans.store import shared_folder

BOTH = {
    "scan_pruned": "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 45 AND l_shipdate >= TIMESTAMP '1995-01-01 00:00:00'",
    "filter_predicates": "SELECT o_orderkey FROM orders WHERE o_totalprice BETWEEN 1000 AND 200000 AND o_orderstatus IN ('F', 'O') AND o_orderpriority LIKE '%-%' AND o_custkey IS NOT NULL",
    "project_case": "SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'middle' ELSE 'large' END AS class, CAST(p_size AS BIGINT) AS size FROM part",
    "join_right": "SELECT n_name, count(s_suppkey) AS n FROM supplier RIGHT JOIN nation ON s_nationkey = n_nationkey GROUP BY n_name",
    "join_full": "SELECT coalesce(c.k, s.k) AS k, coalesce(c.n, 0) AS customers, coalesce(s.n, 0) AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer GROUP BY c_nationkey) c FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier GROUP BY s_nationkey) s ON c.k = s.k",
    "join_theta": "SELECT r_name, count(*) AS n FROM region JOIN nation ON n_regionkey < r_regionkey GROUP BY r_name",
    "join_cross": "SELECT a.r_name AS a, b.r_name AS b FROM region a CROSS JOIN region b",
    "subquery_exists": "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 100000)",
    "agg_hash_two_phase": "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem GROUP BY l_returnflag, l_linestatus",
    "agg_conditional": "SELECT o_orderstatus, count(*) FILTER (WHERE o_totalprice > 100000) AS large, bool_or(o_totalprice > 400000) AS huge FROM orders GROUP BY o_orderstatus",
    "agg_argmax": "SELECT p_brand, max(p_retailprice) AS price, min(p_partkey) AS first_key FROM part GROUP BY p_brand",
    "agg_grouping_sets": "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())",
    "window_lag_lead": "SELECT event_id, coalesce(lag(event_id) OVER w, -1) AS prior, coalesce(lead(event_id) OVER w, -1) AS next, first_value(event_id) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)",
    "window_distribution": "SELECT o_orderkey, CAST(rank() OVER w AS BIGINT) AS r, CAST(dense_rank() OVER w AS BIGINT) AS d, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderpriority)",
    "sort_global": "SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem ORDER BY l_quantity DESC, l_orderkey, l_linenumber LIMIT 100",
    "topk_per_group": "SELECT p_brand, p_partkey FROM (SELECT p_brand, p_partkey, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS rn FROM part) t WHERE rn <= 3",
    "sample_hash": "SELECT p_partkey FROM part WHERE (p_partkey * 7919) % 100 < 10",
    "set_union": "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier",
    "set_union_all": "SELECT k, count(*) AS n FROM (SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier) t GROUP BY k",
    "set_except_all": "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier",
    "fn_string": "SELECT p_partkey, upper(trim(p_name)) AS up, substring(p_brand, 1, 5) AS head, replace(p_type, 'A', 'a') AS swapped, CAST(length(p_name) AS BIGINT) AS len, CAST(levenshtein(p_name, p_type) AS BIGINT) AS distance FROM part",
    "fn_math": "SELECT l_orderkey, l_linenumber, CAST(floor(l_extendedprice) AS BIGINT) AS f, round(sqrt(l_quantity), 6) AS s, round(ln(l_extendedprice), 6) AS l, abs(l_discount - 0.05) < 0.02 AS near FROM lineitem",
    "fn_date": "SELECT o_orderkey, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(month(o_orderdate) AS BIGINT) AS m, CAST(day(o_orderdate) AS BIGINT) AS d, CAST(quarter(o_orderdate) AS BIGINT) AS q FROM orders",
}
VIEWS = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "labels", "pages", "embeddings")


def table(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


def _stream(spark: SparkSession, d: str) -> DataFrame:
    path = f"{d}/events.parquet"
    rows = spark.readStream.schema(spark.read.parquet(path).schema).parquet(d + "/event[s].parquet")
    return rows.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", "1 hour")


def finish(df: DataFrame) -> DataFrame:
    """Run a stream in append mode over all that is there now; rows go to a table in the shared folder."""
    spark, folder = df.sparkSession, shared_folder(df.sparkSession)
    q = df.writeStream.outputMode("append").format("parquet").option("path", f"{folder}/rows").option("checkpointLocation", f"{folder}/state-{uuid.uuid4().hex[:8]}").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{folder}/rows")


def register(query) -> None:
    for name, sql in BOTH.items():

        def run(spark, d, sql=sql):
            for v in VIEWS:
                if v in sql:
                    table(spark, d, v).createOrReplaceTempView(v)
            return spark.sql(sql)

        query(name, sql)(run)

    # ---- sources and sinks

    @query("scan_csv_roundtrip", "SELECT n_nationkey, n_name, n_regionkey FROM nation")
    def scan_csv_roundtrip(spark, d):
        df, path = table(spark, d, "nation"), shared_folder(spark)
        df.write.option("header", True).csv(path)
        return spark.read.schema(df.schema).option("header", True).csv(path)

    @query("scan_json_roundtrip", "SELECT event_id, event_type, value, props FROM events")
    def scan_json_roundtrip(spark, d):
        df, path = table(spark, d, "events").select("event_id", "event_type", "value", "props"), shared_folder(spark)
        df.write.json(path)
        return spark.read.schema(df.schema).json(path)

    @query("scan_orc_roundtrip", "SELECT c_custkey, c_mktsegment FROM customer")
    def scan_orc_roundtrip(spark, d):
        df, path = table(spark, d, "customer").select("c_custkey", "c_mktsegment"), shared_folder(spark)
        df.write.orc(path)
        return spark.read.schema(df.schema).orc(path)

    # ---- joins by strategy

    counts = "SELECT {key} AS k, count(*) AS n FROM {a} JOIN {b} ON {on} GROUP BY 1"

    def joined(name: str, hint: str | None, a: str, b: str, left: str, right: str, key: str) -> None:
        @query(name, counts.format(a=a, b=b, key=key, on=f"{left} = {right}"))
        def run(spark, d):
            other = table(spark, d, b)
            other = other.hint(hint) if hint else other
            return table(spark, d, a).join(other, F.col(left) == F.col(right)).groupBy(F.col(key).alias("k")).agg(F.count(F.lit(1)).alias("n"))

    joined("join_inner_hash", "shuffle_hash", "orders", "customer", "o_custkey", "c_custkey", "c_mktsegment")
    joined("join_sort_merge", "merge", "lineitem", "orders", "l_orderkey", "o_orderkey", "o_orderstatus")
    joined("join_broadcast", "broadcast", "customer", "nation", "c_nationkey", "n_nationkey", "n_name")  # 25 rows at any scale

    @query("join_range_banded", "SELECT a.p_partkey AS a, count(*) AS n FROM part a JOIN part b ON b.p_retailprice BETWEEN a.p_retailprice AND a.p_retailprice + 0.5 GROUP BY 1")
    def join_range_banded(spark, d):
        p = table(spark, d, "part").select("p_partkey", "p_retailprice")
        width = 0.5
        a = p.select(F.col("p_partkey").alias("a"), F.col("p_retailprice").alias("x"), F.explode(F.array(F.floor(F.col("p_retailprice") / width), F.floor(F.col("p_retailprice") / width) + 1)).alias("band"))
        b = p.select(F.col("p_retailprice").alias("y"), F.floor(F.col("p_retailprice") / width).alias("band"))
        return a.join(b, "band").where((F.col("y") >= F.col("x")) & (F.col("y") <= F.col("x") + width)).groupBy("a").agg(F.count(F.lit(1)).alias("n"))

    @query("join_interval", "SELECT a.event_id AS a, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts - INTERVAL 1 HOUR AND a.ts + INTERVAL 1 HOUR GROUP BY 1")
    def join_interval(spark, d):
        e = table(spark, d, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
        hour = 3_600_000_000
        slot = F.floor(F.col("t") / hour)
        a = e.select(F.col("event_id").alias("a"), "user_id", F.col("t").alias("ta"), F.explode(F.array(slot - 1, slot, slot + 1)).alias("slot"))
        b = e.select("user_id", F.col("t").alias("tb"), slot.alias("slot"))
        return a.join(b, ["user_id", "slot"]).where(F.abs(F.col("ta") - F.col("tb")) <= hour).groupBy("a").agg(F.count(F.lit(1)).alias("n"))

    @query("join_lateral_tokens", "SELECT token, count(*) AS n FROM (SELECT unnest(string_split(p_name, ' ')) AS token FROM part) t GROUP BY 1")
    def join_lateral_tokens(spark, d):
        table(spark, d, "part").createOrReplaceTempView("part")
        return spark.sql("SELECT token, count(*) AS n FROM part, LATERAL (SELECT explode(split(p_name, ' ')) AS token) GROUP BY token")

    # ---- aggregates

    @query("agg_sort", "SELECT o_custkey, string_agg(o_orderkey::VARCHAR, ',' ORDER BY o_orderkey) AS keys FROM orders GROUP BY o_custkey")
    def agg_sort(spark, d):
        return table(spark, d, "orders").groupBy("o_custkey").agg(F.array_join(F.transform(F.array_sort(F.collect_list("o_orderkey")), lambda x: x.cast("string")), ",").alias("keys"))

    @query("agg_string", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY n_regionkey")
    def agg_string(spark, d):
        table(spark, d, "nation").createOrReplaceTempView("nation")
        return spark.sql("SELECT n_regionkey, listagg(n_name, ',') WITHIN GROUP (ORDER BY n_name) AS names FROM nation GROUP BY n_regionkey")

    @query("agg_approx_distinct", "SELECT event_type, true AS near FROM events GROUP BY event_type")
    def agg_approx_distinct(spark, d):
        """Whether a merge of daily sketches is within 5 % of the exact count."""
        e = table(spark, d, "events")
        daily = e.groupBy("event_type", F.to_date("ts").alias("day")).agg(F.hll_sketch_agg("user_id").alias("s"))
        got = daily.groupBy("event_type").agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("n"))
        exact = e.groupBy("event_type").agg(F.countDistinct("user_id").alias("m"))
        return got.join(exact, "event_type").select("event_type", (F.abs(F.col("n") - F.col("m")) <= 0.05 * F.col("m") + 1).alias("near"))

    @query("agg_percentiles", "SELECT l_returnflag, round(quantile_cont(l_quantity, 0.5), 6) AS median, round(quantile_cont(l_extendedprice, 0.9), 6) AS p90 FROM lineitem GROUP BY l_returnflag")
    def agg_percentiles(spark, d):
        return table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.percentile("l_quantity", 0.5), 6).alias("median"), F.round(F.percentile("l_extendedprice", 0.9), 6).alias("p90"))

    @query("agg_pivot", "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS F, count(*) FILTER (o_orderstatus = 'O') AS O, count(*) FILTER (o_orderstatus = 'P') AS P FROM orders GROUP BY 1")
    def agg_pivot(spark, d):
        return table(spark, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).na.fill(0)

    @query("unpivot_columns", "SELECT c_custkey, unnest(['c_name','c_mktsegment']) AS field, unnest([c_name, c_mktsegment]) AS value FROM customer")
    def unpivot_columns(spark, d):
        return table(spark, d, "customer").unpivot("c_custkey", ["c_name", "c_mktsegment"], "field", "value")

    @query("window_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS n FROM events")
    def window_range_frame(spark, d):
        w = Window.partitionBy("user_id").orderBy("t").rangeBetween(-86_400_000_000, 0)
        return table(spark, d, "events").withColumn("t", F.unix_micros(F.col("ts").cast("timestamp"))).select("event_id", F.count(F.lit(1)).over(w).alias("n"))

    @query("sort_within_partitions", "SELECT l_orderkey, count(*) AS n FROM lineitem GROUP BY 1")
    def sort_within_partitions(spark, d):
        """Runs of equal keys counted in sorted partitions; a key is in one partition."""
        rows = table(spark, d, "lineitem").select("l_orderkey").repartition("l_orderkey").sortWithinPartitions("l_orderkey")
        return rows.groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("n"))

    # ---- functions

    @query("fn_array", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x)), 4) AS norm, len(list_filter(embedding, lambda x: x > 0)) AS positive, round(list_max(embedding)::DOUBLE, 4) AS top FROM embeddings")
    def fn_array(spark, d):
        norm = F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
        return table(spark, d, "embeddings").select("vec_id", F.round(norm, 4).alias("norm"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"), F.round(F.array_max("embedding").cast("double"), 4).alias("top"))

    @query("fn_map_struct", "SELECT c_custkey, c_name AS name, c_mktsegment AS segment, (length(c_name) > 12)::BIGINT + (length(c_mktsegment) > 12)::BIGINT AS long_values FROM customer")
    def fn_map_struct(spark, d):
        m = F.create_map(F.lit("name"), "c_name", F.lit("segment"), "c_mktsegment")
        kept = F.map_filter(m, lambda k, v: F.length(v) > 12)
        both = F.struct(F.element_at(m, "name").alias("name"), F.element_at(m, "segment").alias("segment"))
        return table(spark, d, "customer").select("c_custkey", both["name"].alias("name"), both["segment"].alias("segment"), F.size(kept).cast("long").alias("long_values"))

    @query("fn_json", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
    def fn_json(spark, d):
        return table(spark, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"))

    @query("fn_url_html", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, CAST(length(regexp_replace(html, '<[^>]*>', '', 'g')) AS BIGINT) AS text_length FROM pages")
    def fn_url_html(spark, d):
        return table(spark, d, "pages").select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.length(F.regexp_replace("html", "<[^>]*>", "")).cast("long").alias("text_length"))

    # ---- functions of the user's own

    @query("udf_arrow_scalar", "SELECT p_partkey, CAST(length(p_name) - length(replace(p_name, ' ', '')) + 1 AS BIGINT) AS words FROM part")
    def udf_arrow_scalar(spark, d):
        @F.pandas_udf("long")
        def words(x: pd.Series) -> pd.Series:
            return x.str.count(" ") + 1

        return table(spark, d, "part").select("p_partkey", words("p_name").alias("words"))

    @query("udaf_grouped", "SELECT p_brand, round(max(p_retailprice) - min(p_retailprice), 6) AS spread FROM part GROUP BY p_brand")
    def udaf_grouped(spark, d):
        @F.pandas_udf("double")
        def spread(x: pd.Series) -> float:
            return float(round(x.max() - x.min(), 6))

        return table(spark, d, "part").groupBy("p_brand").agg(spread("p_retailprice").alias("spread"))

    @query("sql_udf_dup", "WITH g AS (SELECT p_brand, count(*) AS n FROM part GROUP BY 1), s AS (SELECT sum(n)::BIGINT AS c, count_if(n = 1)::BIGINT AS u, count(*) AS p FROM g) SELECT round((2.0 * c - u - p + 1) / (2.0 * c), 6)::DOUBLE AS dup FROM s")
    def sql_udf_dup(spark, d):
        spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sheetgraph_dup(c BIGINT, u BIGINT, p BIGINT) RETURNS DOUBLE RETURN CASE WHEN c <= 1 THEN 0D ELSE (2D * c - u - p + 1) / (2D * c) END")
        table(spark, d, "part").createOrReplaceTempView("part")
        return spark.sql("SELECT sheetgraph_dup(c, u, p) AS dup FROM (SELECT sum(n) AS c, count_if(n = 1) AS u, count(*) AS p FROM (SELECT p_brand, count(*) AS n FROM part GROUP BY p_brand))").select(F.round("dup", 6).alias("dup"))

    @query("udtf_predict", "SELECT 'orders' AS sheet_id, 'o_orderpriority' AS col, 'T10' AS template UNION ALL SELECT 'orders', 'o_orderstatus', 'T11'")
    def udtf_predict(spark, d):
        """The prediction as a table function over sheet-local cells: one sheet is one group."""
        from pyspark.sql.functions import udtf

        from sheetgraph.operators.tree import predict_values

        @udtf(returnType="sheet_id string, col string, template string")
        class PredictMapping:
            def __init__(self):
                self.columns, self.sheet = {}, None

            def eval(self, row):
                self.sheet = row["sheet_id"]
                self.columns.setdefault(row["col"], []).append(row["s"])

            def terminate(self):
                for col, values in self.columns.items():
                    yield self.sheet, col, predict_values(values)

        spark.udtf.register("predict_mapping", PredictMapping)
        o = table(spark, d, "orders")
        o.select(F.lit("orders").alias("sheet_id"), F.inline(F.array(*[F.struct(F.lit(c).alias("col"), F.col(c).alias("s")) for c in ("o_orderstatus", "o_orderpriority")]))).createOrReplaceTempView("sheet_cells")
        return spark.sql("SELECT * FROM predict_mapping(TABLE(sheet_cells) PARTITION BY sheet_id)")

    # ---- streams, run over all that is there, in append mode: windows that the watermark has closed

    closed = "(SELECT max(ts) - INTERVAL 1 HOUR FROM events)"

    @query("stream_sliding", f"SELECT w AS start, count(*) AS n FROM (SELECT unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS w FROM events) t WHERE w + INTERVAL 2 DAY <= {closed} GROUP BY 1")
    def stream_sliding(spark, d):
        out = _stream(spark, d).groupBy(F.window("at", "2 days", "1 day")).agg(F.count(F.lit(1)).alias("n"))
        return finish(out.select(F.col("window.start").alias("start"), "n")).select(F.col("start").cast("timestamp_ntz").alias("start"), "n")

    @query("stream_session", f"WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, k HAVING max(ts) + INTERVAL 6 HOUR <= {closed}")
    def stream_session(spark, d):
        out = _stream(spark, d).groupBy("user_id", F.session_window("at", "6 hours")).agg(F.count(F.lit(1)).alias("n"))
        return finish(out.select("user_id", F.col("session_window.start").alias("start"), "n")).select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n")

    @query("stream_dedup", "SELECT DISTINCT event_id FROM events")
    def stream_dedup(spark, d):
        return finish(_stream(spark, d).dropDuplicatesWithinWatermark(["event_id"]).select("event_id"))

    @query("stream_static_join", "SELECT event_id, c_mktsegment AS segment FROM events JOIN customer ON user_id = c_custkey")
    def stream_static_join(spark, d):
        c = table(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), F.col("c_mktsegment").alias("segment"))
        return finish(_stream(spark, d).join(c, "user_id").select("event_id", "segment"))

    @query("stream_interval_join", "SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 DAY")
    def stream_interval_join(spark, d):
        a = _stream(spark, d).where("event_type = 'click'").select(F.col("event_id").alias("click"), "user_id", F.col("at").alias("ta"))
        b = _stream(spark, d).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("buyer"), F.col("at").alias("tb"))
        return finish(a.join(b, F.expr("user_id = buyer AND tb >= ta AND tb <= ta + INTERVAL 1 DAY")).select("click", "purchase"))

    query("stream_late_rows", "SELECT 0::BIGINT AS late_rows_kept, count(*) AS in_time FROM events")(late_rows)


def late_rows(spark: SparkSession, d: str) -> DataFrame:
    """Events, then copies two days older than the watermark in a later batch: the late ones leave no trace."""
    folder = shared_folder(spark)
    events = table(spark, d, "events").select("event_id", "ts")
    events.write.parquet(f"{folder}/in")
    schema = events.schema
    state, rows = f"{folder}/state", f"{folder}/rows"

    def run() -> None:
        s = spark.readStream.schema(schema).parquet(f"{folder}/in").withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", "1 hour")
        s.dropDuplicatesWithinWatermark(["event_id"]).select("event_id").writeStream.format("parquet").option("path", rows).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()

    run()
    oldest = events.agg(F.min("ts").alias("first"))
    late = events.crossJoin(F.broadcast(oldest)).select((-F.col("event_id") - 1).alias("event_id"), (F.col("first") - F.expr("INTERVAL 2 DAYS")).alias("ts"))  # one row
    late.write.mode("append").parquet(f"{folder}/in")
    run()
    got = spark.read.schema("event_id long").parquet(rows)
    return got.agg(F.count_if(F.col("event_id") < 0).alias("late_rows_kept"), F.count_if(F.col("event_id") >= 0).alias("in_time"))
