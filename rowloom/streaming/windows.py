"""Runs over streams: windowed counts, keyed state, and reordering of micro-batches.

The reordering methods are batch methods; blocks make micro-batches natural units for them."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from rowloom.operators.order import order_by


def event_stream(spark: SparkSession, folder: str, files: int = 1) -> DataFrame:
    """The event table as a stream of files, with zoned timestamps (a watermark wants them)."""
    schema = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(folder)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))



def tumbling(events: DataFrame, width: str = "1 day", late: str = "1 hour") -> DataFrame:
    """Rows and top value of every window and event type."""
    frame = events.withWatermark("ts", late) if events.isStreaming else events
    return frame.groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n"), F.max("value").alias("top_value"))


def sliding(events: DataFrame, width: str = "2 days", step: str = "1 day", late: str = "1 hour") -> DataFrame:
    frame = events.withWatermark("ts", late) if events.isStreaming else events
    return frame.groupBy(F.window("ts", width, step), "event_type").agg(F.count("*").alias("n"), F.max("value").alias("top_value"))


def sessions(events: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """Sessions of each user."""
    frame = events.withWatermark("ts", late) if events.isStreaming else events
    return frame.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"), F.max("value").alias("top_value"))


def running_runs(events: DataFrame) -> DataFrame:
    """(user_id, n, runs): rows and runs of event_type for each user so far, in event order.

    The state of a key is its last event type and two counts: runs add up over micro-batches, since
    only the border between two of them has to be looked at."""

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, runs, last = state.get if state.exists else (0, 0, None)
        for pdf in batches:
            for kind in pdf.sort_values(["ts", "event_id"])["event_type"]:
                runs += int(n == 0 or kind != last)
                last, n = kind, n + 1
        state.update((n, runs, last))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "runs": [runs]})

    return events.groupBy("user_id").applyInPandasWithState(
        update, "user_id long, n long, runs long", "n long, runs long, last string", "update", GroupStateTimeout.NoTimeout
    )


def drain(stream: DataFrame, path: str, mode: str, checkpoint: str) -> DataFrame:
    """Runs a stream over all available input into Parquet files under `path`, and reads them back: in
    `complete` mode the last micro-batch, which has the whole result, else all of them."""
    last = {"batch": -1}

    def write(batch: DataFrame, number: int) -> None:
        # a batch that is run again replaces its own files only
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")
        last["batch"] = max(last["batch"], number)

    query = stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    spark = stream.sparkSession
    if last["batch"] < 0:
        return spark.createDataFrame([], stream.schema)
    part = f"{path}/batch={last['batch']}" if mode == "complete" else path
    return spark.read.schema(stream.schema).parquet(part).select(*stream.columns)


def reorder_sink(stream: DataFrame, path: str, cols: list[str], checkpoint: str, order: str = "interleave") -> None:
    """Reorders each micro-batch as a block and appends it, tagged with its batch number."""
    query = stream.writeStream.foreachBatch(reorder_batch(path, cols, order)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()


def reorder_batch(path: str, cols: list[str], order: str) -> Callable[[DataFrame, int], None]:
    def write(batch: DataFrame, number: int) -> None:
        # a batch that is run again replaces its own files only
        order_by(batch, order, cols).withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return write
