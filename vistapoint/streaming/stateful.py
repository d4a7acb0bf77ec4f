"""Stateful streams: running totals of tiles with timers, and what a watermark leaves out."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle, StreamingQuery

from .ingest import timed

ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
PROVIDER = "spark.sql.streaming.stateStore.providerClass"
REPORT = "tile_x long, tile_y long, version long, n long, videos long"


class TileTotals(StatefulProcessor):
    """For each tile, how many fields of view and videos it has seen. A timer after its last event reports the totals.

    The state of a tile is a count and a map entry for each of its videos, so no tile's state is one growing value.
    """

    def __init__(self, quiet_ms: int) -> None:
        self.quiet_ms = quiet_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.totals = handle.getValueState("totals", "n long, videos long, version long")
        self.videos = handle.getMapState("videos", "video_id long", "seen boolean")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        n, videos, version = self.totals.get() if self.totals.exists() else (0, 0, 0)
        latest = 0
        for part in rows:
            n += len(part)
            latest = max(latest, int(part["t"].max().timestamp() * 1000))
            for video in part["video_id"].unique().tolist():
                if not self.videos.containsKey((video,)):
                    self.videos.updateValue((video,), (True,))
                    videos += 1
        self.totals.update((n, videos, version))
        for timer in list(self.handle.listTimers()):
            self.handle.deleteTimer(timer)
        self.handle.registerTimer(max(latest + self.quiet_ms, timerValues.getCurrentWatermarkInMs() + 1) - 1)
        yield pd.DataFrame(columns=["tile_x", "tile_y", "version", "n", "videos"])

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        n, videos, version = self.totals.get()
        self.totals.update((n, videos, version + 1))
        yield pd.DataFrame({"tile_x": [key[0]], "tile_y": [key[1]], "version": [version + 1], "n": [n], "videos": [videos]})

    def close(self) -> None:
        pass


def tile_totals(fovs: DataFrame, degrees: float = 0.1, delay: str = "0 seconds", quiet_ms: int = 0) -> DataFrame:
    """A streaming table of REPORT: a tile's totals, once the watermark has come ``quiet_ms`` past its last event."""
    placed = timed(fovs, delay).select(F.floor(F.col("lon") / degrees).alias("tile_x"), F.floor(F.col("lat") / degrees).alias("tile_y"), "t", "video_id")
    return placed.groupBy("tile_x", "tile_y").transformWithStateInPandas(TileTotals(quiet_ms), REPORT, "append", "EventTime")


def report_tiles(fovs: DataFrame, path: str, checkpoint: str) -> None:
    """Run what is there through ``tile_totals`` into ``path``. The store of such states is RocksDB, which is set for this run only."""
    spark = fovs.sparkSession
    before = spark.conf.get(PROVIDER)
    spark.conf.set(PROVIDER, ROCKS)
    try:
        tile_totals(fovs).writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).outputMode("append").start().awaitTermination()
    finally:
        spark.conf.set(PROVIDER, before)


def latest_reports(reports: DataFrame) -> DataFrame:
    """The last report of each tile."""
    return reports.groupBy("tile_x", "tile_y").agg(F.max_by(F.struct("n", "videos"), "version").alias("r")).select("tile_x", "tile_y", "r.n", "r.videos")


def late_rows(query: StreamingQuery) -> int:
    """How many rows the watermark has left out so far, over all stateful operators of a query."""
    return sum(int(op["numRowsDroppedByWatermark"]) for p in query.recentProgress for op in p["stateOperators"])
