"""Fields of view that arrive as a stream: bounding boxes at ingestion, windows with watermarks, and an additive cube."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.noise import u01  # noqa: F401  carriers are deterministic in streams too
from ..operators.matrix import exploded
from ..plans.query import Query
from ..sources import carriers, store

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def ingest(events: DataFrame, path: str, checkpoint: str, variant: str = "pie60"):
    """Append arriving events to the store as fields of view with their boxes; runs until what is there has been read."""
    fovs = store.laid_out(carriers.events_to_fovs(events, variant))
    return fovs.writeStream.format("parquet").partitionBy("day").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).outputMode("append").start()


def timed(fovs: DataFrame, delay: str = "1 hour") -> DataFrame:
    """With t as a timestamp under a watermark; a local timestamp cannot carry one."""
    return fovs.withColumn("t", F.col("t").cast("timestamp")).withWatermark("t", delay)


def window_counts(fovs: DataFrame, kind: str = "tumbling") -> DataFrame:
    """win_start, win_end, n (and video_id for sessions): fields of view in daily, overlapping six-hourly, or session windows."""
    t = F.col("t").cast("timestamp") if dict(fovs.dtypes)["t"] != "timestamp" else F.col("t")
    if kind == "session":
        grouped = fovs.groupBy(F.session_window(t, "6 hours").alias("w"), "video_id")
    else:
        grouped = fovs.groupBy((F.window(t, "1 day") if kind == "tumbling" else F.window(t, "1 day", "6 hours")).alias("w"))
    keys = ["video_id"] if kind == "session" else []
    return grouped.agg(F.count("*").alias("n")).select(*keys, F.col("w.start").cast("timestamp_ntz").alias("win_start"), F.col("w.end").cast("timestamp_ntz").alias("win_end"), "n")


def deduplicated(fovs: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Each id once within the watermark."""
    return timed(fovs, delay).dropDuplicatesWithinWatermark(["fov_id"])


def maintain_cube(fovs: DataFrame, query: Query, path: str, checkpoint: str):
    """Append each micro-batch's sums by day and cell, under the batch's number: a batch that is run again replaces its own."""

    def add(batch: DataFrame, number: int) -> None:
        dated = batch.withColumn("day", F.to_date("t"))
        sums = exploded(dated, query, ("day",)).groupBy("day", "cell_x", "cell_y").agg(F.sum("ci_fixed").alias("ci_fixed"))
        sums.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return fovs.writeStream.foreachBatch(add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
