"""Event streams: windowed sufficient statistics, joins, state."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def source(spark: SparkSession, folder: str, delay: str = "10 minutes", files_per_batch: int = 1, glob: str = "events*.parquet") -> DataFrame:
    """Files of the folder as a stream with a watermark on ts (UTC)."""
    raw = spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", files_per_batch).option("pathGlobFilter", glob).parquet(folder)
    return raw.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def window_moments(events: DataFrame, length: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Per window: n, sums of x, x^2, y, xy of value against the JSON k."""
    y = F.from_json("props", "k int")["k"].cast("double")
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.withColumn("y", y).groupBy(w.alias("w")).agg(
        F.count("*").alias("n"), F.sum("value").alias("sx"), F.sum(F.col("value") * F.col("value")).alias("sxx"),
        F.sum("y").alias("sy"), F.sum(F.col("value") * F.col("y")).alias("sxy"),
    ).select(F.col("w.start").alias("start"), "n", "sx", "sxx", "sy", "sxy")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def unique(events: DataFrame) -> DataFrame:
    """Each event once within the watermark."""
    return events.dropDuplicatesWithinWatermark(["event_id"])


def follows(events: DataFrame, first: str, second: str, within: str = "1 hour") -> DataFrame:
    """Stream-stream join: the second kind of event within a time after the first, by user."""
    a = events.filter(F.col("event_type") == first).select(F.col("user_id").alias("user"), F.col("ts").alias("ts_first"))
    b = events.filter(F.col("event_type") == second).select("user_id", F.col("ts").alias("ts_second"))
    return a.join(b, F.expr(f"user = user_id AND ts_second >= ts_first AND ts_second <= ts_first + INTERVAL {within}")).drop("user")


def outliers(events: DataFrame, factor: float = 2.0) -> DataFrame:
    """event_id, user_id, h: events whose leverage in their user's history so far is over
    factor times the average; state per user is three sums."""

    def run(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, sx, sxx = state.get if state.exists else (0, 0.0, 0.0)
        out = []
        for frame in frames:
            for event, x in frame.sort_values("event_id")[["event_id", "value"]].itertuples(index=False):
                n, sx, sxx = n + 1, sx + x, sxx + x * x
                spread = sxx - sx * sx / n
                h = 1 / n + ((x - sx / n) ** 2 / spread if spread > 1e-12 else 0.0)
                if n >= 5 and h > factor * 2 / n:
                    out.append((int(event), int(key[0]), float(h)))
        state.update((n, sx, sxx))
        yield pd.DataFrame(out, columns=["event_id", "user_id", "h"])

    return events.groupBy("user_id").applyInPandasWithState(run, "event_id long, user_id long, h double", "n long, sx double, sxx double", "append", "NoTimeout")


def run_once(stream: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Drains what is there into a memory table of that name (tests and small results)."""
    writer = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    if checkpoint:
        writer = writer.option("checkpointLocation", checkpoint)
    query = writer.start()
    query.awaitTermination()
    return stream.sparkSession.table(name)


def merge_into(stream: DataFrame, path: str, keys: tuple[str, ...], checkpoint: str):
    """foreachBatch upsert into a Parquet table: each batch id is its own folder, so a
    repeated batch replaces itself; the latest batch wins on read."""

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.outputMode("update").option("checkpointLocation", checkpoint).foreachBatch(write).trigger(availableNow=True).start()
