"""Streaming over the events: windows, sessions, late rows, deduplication, joins and own state.

Streams read files, and each run ends when all there is has been read. Batches are written to the shared
folder; nothing is held by the driver.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState

from beamrank.sources.io import shared_folder
from beamrank.sources.tables import table


def read_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream. A watermark needs a timestamp with zone; the session's zone gives the same reading."""
    schema = table(spark, sf_dir, "events").schema
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/events.parquet*")
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def finished(stream: DataFrame, mode: str) -> DataFrame:
    """Run the stream over all that is there and return what it has written."""
    spark = stream.sparkSession
    out, state = shared_folder(spark, "stream"), shared_folder(spark, "state")

    def keep(batch: DataFrame, epoch: int) -> None:
        # a whole result replaces the one before; a batch that runs again replaces itself
        batch.write.mode("overwrite").parquet(out if mode == "complete" else f"{out}/epoch={epoch}")

    q = stream.writeStream.outputMode(mode).option("checkpointLocation", state).trigger(availableNow=True).foreachBatch(keep).start()
    q.awaitTermination()
    if mode == "complete":
        return spark.read.schema(stream.schema).parquet(out)
    return spark.read.schema(stream.schema).option("recursiveFileLookup", True).parquet(out)


def tumbling(events: DataFrame, width: str = "1 day") -> DataFrame:
    w = events.withWatermark("ts", "1 hour").groupBy(F.window("ts", width), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("value").cast("decimal(18,2)")).alias("v"))
    return w.select(F.col("window.start").cast("timestamp_ntz").alias("start"), "event_type", "n", F.col("v").cast("double").alias("v"))


def sliding(events: DataFrame, width: str = "1 day", step: str = "12 hours") -> DataFrame:
    w = events.withWatermark("ts", "1 hour").groupBy(F.window("ts", width, step)).agg(F.count(F.lit(1)).alias("n"))
    return w.select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    w = events.withWatermark("ts", "1 hour").groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return w.select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), "n")


def deduplicated(events: DataFrame, *keys: str) -> DataFrame:
    """Each key once."""
    return events.dropDuplicates(list(keys)).select(*keys)


def with_static(events: DataFrame, static: DataFrame, on, by: str) -> DataFrame:
    """Counts of arrivals by a property of a static table."""
    return events.join(static, on).groupBy(by).agg(F.count(F.lit(1)).alias("n"))


def running_precision(events: DataFrame) -> DataFrame:
    """Accepted and right so far for each user, as own state."""

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        accepted, right = state.get if state.exists else (0, 0)
        for b in batches:
            accepted += int((b["value"] >= 50).sum())
            right += int(((b["value"] >= 50) & (b["event_type"] == "purchase")).sum())
        state.update((accepted, right))
        yield pd.DataFrame({"user_id": [key[0]], "accepted": [accepted], "right_ones": [right]})

    return events.select("user_id", "value", "event_type").groupBy("user_id").applyInPandasWithState(
        update, "user_id bigint, accepted bigint, right_ones bigint", "accepted bigint, right_ones bigint", "update", "NoTimeout"
    )


def late_rows(spark: SparkSession, sf_dir: str, split: str = "2024-01-15") -> DataFrame:
    """Daily counts of a stream whose first file holds the later half: rows of the second file come too late."""
    events = table(spark, sf_dir, "events")
    folder = shared_folder(spark, "late")
    schema = events.schema
    events.where(F.col("ts") >= split).coalesce(1).write.mode("append").parquet(folder)
    first = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(folder)
    daily = first.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n"))
    daily = daily.select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")
    out, state = shared_folder(spark, "stream"), shared_folder(spark, "state")
    for _ in range(2):
        q = daily.writeStream.outputMode("append").format("parquet").option("path", out).option("checkpointLocation", state).trigger(availableNow=True).start()
        q.awaitTermination()
        events.where(F.col("ts") < split).coalesce(1).write.mode("append").parquet(folder)
    return spark.read.schema(daily.schema).parquet(out)
