"""Structured Streaming: regularise, score against learned fences, regions, reviews, per-slot state."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def meter_stream(spark: SparkSession, folder: str, schema, files_per_trigger: int = 4) -> DataFrame:
    """Parquet files of a folder as they come, event time as a time stamp with zone (watermarks need one)."""
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def hourly(stream: DataFrame, key: str, late: str = "2 hours") -> DataFrame:
    """Tumbling hours: series_id, hour, y; hours beyond the watermark are final."""
    w = stream.withWatermark("ts", late).groupBy(F.window("ts", "1 hour"), F.col(key).cast("string").alias("series_id"))
    return w.agg((F.sum(F.round(F.col("value") * 100).cast("bigint")) / 100.0).alias("y")).select(
        "series_id", F.col("window.start").alias("hour"), "y"
    )


def sliding_medians(stream: DataFrame, key: str, late: str = "2 hours") -> DataFrame:
    """Day-long windows each hour: approximate median of the values, as a sign of drift."""
    w = stream.withWatermark("ts", late).groupBy(F.window("ts", "24 hours", "1 hour"), F.col(key).cast("string").alias("series_id"))
    return w.agg(F.percentile_approx("value", 0.5).alias("median")).select("series_id", F.col("window.end").alias("until"), "median")


def without_repeats(stream: DataFrame, key: str = "event_id", late: str = "2 hours") -> DataFrame:
    """Repeated meter messages inside the watermark go."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


#: Fence rows that may be broadcast to a stream.
FENCE_ROWS = 200_000


def score(samples: DataFrame, fences: DataFrame, period_hours: int = 24) -> DataFrame:
    """Stream-static join: each sample's slot fences, and whether it lies outside.

    The learned table is counted: up to ``FENCE_ROWS`` rows are broadcast, more join by shuffle on their keys.
    """
    slot = F.pmod(F.floor(F.unix_timestamp("hour") / 3600), F.lit(period_hours)).cast("int")
    f = fences.select("series_id", "slot", "lo", "hi")
    f = F.broadcast(f) if f.count() <= FENCE_ROWS else f
    joined = samples.withColumn("slot", slot).join(f, ["series_id", "slot"], "left")
    return joined.withColumn("is_outlier", F.coalesce((F.col("y") < F.col("lo")) | (F.col("y") > F.col("hi")), F.lit(False)))


def regions(flagged: DataFrame, time: str = "hour", gap: str = "3 hours", late: str = "2 hours") -> DataFrame:
    """Session windows over flagged samples: runs of outliers no farther apart than ``gap``."""
    w = flagged.where("is_outlier").withWatermark(time, late).groupBy("series_id", F.session_window(time, gap))
    return w.agg(F.count("*").alias("n")).select("series_id", F.col("session_window.start").alias("first"), F.col("session_window.end").alias("until"), "n")


def reviewed(flagged: DataFrame, verdicts: DataFrame, late: str = "2 hours", within: str = "1 day") -> DataFrame:
    """Stream-stream join: verdicts (series_id, hour, decided_at, verdict) that follow a sample within a day."""
    a = flagged.withWatermark("hour", late).alias("a")
    b = verdicts.withWatermark("decided_at", late).alias("b")
    on = F.expr(f"a.series_id = b.series_id and a.hour = b.hour and b.decided_at >= a.hour and b.decided_at <= a.hour + interval {within}")
    return a.join(b, on).select("a.series_id", "a.hour", "a.y", "b.verdict")


def slot_state(samples: DataFrame, keep: int = 60) -> DataFrame:
    """Running (theta, mad) of each (series, slot) over its last ``keep`` values, updated with each micro-batch.

    ``samples`` holds series_id, slot, hour, y. State is a bounded list of values per key.
    """

    def update(key, frames, state):
        held = list(state.get[0]) if state.exists else []
        for pdf in frames:
            held += pdf.sort_values("hour")["y"].tolist()
        held = held[-keep:]
        state.update((held,))
        v = pd.Series(held, dtype=float)
        theta = v.median()
        yield pd.DataFrame({"series_id": [key[0]], "slot": [key[1]], "theta": [theta], "mad": [(v - theta).abs().median()], "n": [len(v)]})

    return samples.groupBy("series_id", "slot").applyInPandasWithState(
        update, "series_id string, slot int, theta double, mad double, n long", "held array<double>", "update", "NoTimeout"
    )


def write_clean(scored: DataFrame, path: str, checkpoint: str):
    """Sink: each micro-batch appended as Parquet under its batch number, so that a retried batch replaces itself."""

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return scored.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
