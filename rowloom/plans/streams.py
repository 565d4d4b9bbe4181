"""Streaming queries over the event table, each with its batch twin in SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from rowloom.plans.registry import query
from rowloom.sources.io import read_table
from rowloom.sources.scratch import scratch_path
from rowloom.streaming import windows as X


def _replay(spark: SparkSession, sf_dir: str) -> str:
    """The event table as four files in time order, so that a stream has several micro-batches."""
    path = scratch_path(spark, "events")
    events = read_table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "value", "props")
    for week in range(4):
        part = events.where(F.least(F.floor((F.dayofmonth("ts") - 1) / 8), F.lit(3)) == week)
        part.coalesce(1).write.mode("append").parquet(path)
    return path


def _drained(spark: SparkSession, stream: DataFrame, mode: str) -> DataFrame:
    return X.drain(stream, scratch_path(spark, "drained"), mode, scratch_path(spark, "checkpoint"))


_COLS = ["start", "event_type", "n", "top_value"]


def _framed(df: DataFrame) -> DataFrame:
    return df.select(F.unix_timestamp("window.start").alias("start"), "event_type", "n", "top_value")


@query("stream_tumbling", "SELECT CAST(epoch(date_trunc('day', ts)) AS BIGINT) AS start, event_type, count(*) AS n, max(value) AS top_value FROM events GROUP BY ALL")
def stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    stream = X.tumbling(X.event_stream(spark, _replay(spark, sf_dir)), late="60 days")
    return _framed(_drained(spark, stream, "complete"))


@query(
    "stream_sliding",
    "SELECT CAST(epoch(day) - 86400 * k AS BIGINT) AS start, event_type, count(*) AS n, max(value) AS top_value FROM (SELECT date_trunc('day', ts) AS day, * FROM events), (VALUES (0), (1)) t(k) GROUP BY ALL",
)
def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    stream = X.sliding(X.event_stream(spark, _replay(spark, sf_dir)), late="60 days")
    return _framed(_drained(spark, stream, "complete"))


@query(
    "stream_session",
    "WITH o AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events), "
    "s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM o) "
    "SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, count(*) AS n, max(value) AS top_value FROM s GROUP BY user_id, k",
)
def stream_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    stream = X.sessions(X.event_stream(spark, _replay(spark, sf_dir)), late="60 days")
    return _drained(spark, stream, "complete").select("user_id", F.unix_timestamp("session_window.start").alias("start"), "n", "top_value")


@query(
    "stream_running_runs",
    "SELECT user_id, count(*) AS n, CAST(sum(new) AS BIGINT) AS runs FROM (SELECT user_id, CASE WHEN event_type IS DISTINCT FROM lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) THEN 1 ELSE 0 END AS new FROM events) GROUP BY 1",
)
def stream_running_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Keyed state over micro-batches; the last update of each key is the batch result."""
    updates = _drained(spark, X.running_runs(X.event_stream(spark, _replay(spark, sf_dir))), "update")
    last = W.partitionBy("user_id").orderBy(F.desc("n"))
    return updates.withColumn("rn", F.row_number().over(last)).where("rn = 1").drop("rn")


def _deal_reversed(events: DataFrame, path: str) -> None:
    """All events as three files, late days of the month first; rows without a time go with the last."""
    day = F.coalesce(F.dayofmonth("ts"), F.lit(1))
    for low, high in ((20, 32), (10, 20), (1, 10)):
        events.where((day >= low) & (day < high)).coalesce(1).write.mode("append").parquet(path)


@query("stream_late_rows", "SELECT true AS dropped_some, true AS none_doubled")
def stream_late_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Files in reverse time order: rows behind the watermark are dropped, and no row counts twice."""
    path = scratch_path(spark, "late")
    events = read_table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "value", "props")
    _deal_reversed(events, path)
    total = spark.read.parquet(path).count()
    stream = X.tumbling(X.event_stream(spark, path), late="1 hour")
    got = _drained(spark, stream, "append").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))
    return got.select((F.col("n") < total).alias("dropped_some"), (F.col("n") <= total).alias("none_doubled"))


@query("stream_reorder_sink", "SELECT count(*) AS n, CAST(4 AS BIGINT) AS batches, CAST(0 AS BIGINT) AS broken FROM events")
def stream_reorder_sink(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each micro-batch is one reordered block with positions of its own."""
    out = scratch_path(spark, "blocks")
    cols = ["event_type", "user_id"]
    X.reorder_sink(X.event_stream(spark, _replay(spark, sf_dir)), out, cols, scratch_path(spark, "checkpoint"))
    blocks = spark.read.parquet(out).groupBy("batch").agg(F.count("*").alias("n"), F.max("pos").alias("last"), F.count_distinct("pos").alias("places"))
    return blocks.agg(F.sum("n").alias("n"), F.count("*").alias("batches"), F.count_if((F.col("last") + 1 != F.col("n")) | (F.col("places") != F.col("n"))).alias("broken"))
