"""Streams of events: windowed counts and running column profiles, run to completion over a file source."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sheetgraph.operators.heuristics import dup
from sheetgraph.plans.store import shared_folder


def read_events(spark: SparkSession, d: str) -> DataFrame:
    path = f"{d}/events.parquet"
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).parquet(path + "*")


def _finish(df: DataFrame, mode: str) -> DataFrame:
    """Run with all that is there now, then give the sink's table."""
    spark, name = df.sparkSession, f"out_{uuid.uuid4().hex[:10]}"
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", shared_folder(spark)).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def daily_counts(spark: SparkSession, d: str) -> DataFrame:
    """Events by day and type; complete mode, so the last open day counts too."""
    ts = F.col("ts").cast("timestamp")
    rows = read_events(spark, d).withColumn("at", ts).withWatermark("at", "1 hour")
    out = _finish(rows.groupBy(F.window("at", "1 day"), "event_type").agg(F.count(F.lit(1)).alias("n")), "complete")
    return out.select(F.col("window.start").cast("timestamp_ntz").alias("day"), "event_type", "n")


def running_dup(spark: SparkSession, d: str, column: str) -> DataFrame:
    """The degree of duplication of a column out of a streamed value dictionary."""
    counts = _finish(read_events(spark, d).groupBy(column).agg(F.count(F.lit(1)).alias("cnt")), "complete")
    got = counts.agg(F.sum("cnt").alias("c"), F.count_if(F.col("cnt") == 1).alias("u"), F.count(F.lit(1)).alias("p"))
    return got.withColumn("dup", F.round(dup(F.col("c"), F.col("u"), F.col("p")), 6))
