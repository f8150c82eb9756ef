"""Streams of pixels against static runs.

A zone layer's runs need raster metadata only, so they are made once and measurements may
arrive later: every micro-batch joins new pixels with the runs, and per-zone state is kept.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..functions.accumulate import value_aggs
from ..functions.arith import floor_div, long
from ..functions.grid import GridMeta, RasterLayer
from ..operators import merge_ordered as mo
from ..operators import selection
from ..operators.zones import ChunkSpec, ZoneLayer


def source(spark: SparkSession, folder: str, schema, files_per_trigger: int = 1) -> DataFrame:
    """New Parquet files of a folder as they come."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)


def event_pixels(events: DataFrame, meta: GridMeta) -> DataFrame:
    k = F.col("event_id").cast("long")
    return events.select(F.pmod(k, long(meta.cols)).alias("x"), floor_div(k, meta.cols).alias("y"), F.round(F.col("value") * 100).cast("long").alias("v"), "ts", "event_id")


def zone_stream(pixels: DataFrame, zones: ZoneLayer, meta: GridMeta) -> DataFrame:
    """(zone_id, v, and the pixels' other columns) of a stream or a batch."""
    runs = mo.intersect(zones, meta, ChunkSpec("none")).select("zone_id", "tile_id", "y", "x0", "x1")
    return selection.range_join(RasterLayer(pixels, meta), runs, selection.resolved("auto", zones, meta))


def running_stats(pixels: DataFrame, zones: ZoneLayer, meta: GridMeta) -> DataFrame:
    """Per-zone statistics so far; for update or complete mode."""
    met = zone_stream(pixels, zones, meta)
    return met.groupBy("zone_id").agg(*value_aggs(of=met))


def without_repeats(pixels: DataFrame, delay: str = "2 hours") -> DataFrame:
    """Pixels sent twice within the watermark count once."""
    return pixels.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def _watermarked(pairs: DataFrame, delay: str | None) -> DataFrame:
    """Watermarks need times with a zone: times without one are read in the session's."""
    if not delay:
        return pairs
    return pairs.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def windowed(pairs: DataFrame, width: str = "1 day", slide: str | None = None, delay: str | None = "2 hours") -> DataFrame:
    """Tumbling or sliding windows a zone; with a delay late rows are dropped."""
    pairs = _watermarked(pairs, delay)
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    got = pairs.groupBy(w.alias("w"), "zone_id").agg(*value_aggs(("count", "sum"), pairs))
    return got.select("zone_id", F.col("w.start").alias("start"), "cnt", "sum_v")


def sessions(pairs: DataFrame, gap: str = "2 hours", delay: str | None = "2 hours") -> DataFrame:
    """Runs of activity a zone, ended by a gap."""
    pairs = _watermarked(pairs, delay)
    got = pairs.groupBy(F.session_window("ts", gap).alias("w"), "zone_id").agg(F.count(F.lit(1)).alias("cnt"))
    return got.select("zone_id", F.col("w.start").alias("start"), F.col("w.end").alias("finish"), "cnt")


class ZoneAccumulator(StatefulProcessor):
    """A user's accumulator as per-zone state with a time to live."""

    def __init__(self, ttl_ms: int | None = None):
        self.ttl = ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("stats", "cnt bigint, sum_v bigint, min_v bigint, max_v bigint", self.ttl)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        now = self.state.get() if self.state.exists() else None
        for df in rows:
            v = df["v"]
            add = (len(v), int(v.sum()), int(v.min()), int(v.max()))
            now = add if now is None else (now[0] + add[0], now[1] + add[1], min(now[2], add[2]), max(now[3], add[3]))
        self.state.update(tuple(now))
        yield pd.DataFrame({"zone_id": [key[0]], "cnt": [now[0]], "sum_v": [now[1]], "min_v": [now[2]], "max_v": [now[3]]})

    def close(self) -> None:
        pass


def stateful_stats(pairs: DataFrame, ttl_ms: int | None = None) -> DataFrame:
    """Running statistics by ``transformWithStateInPandas``; needs the RocksDB state store."""
    return pairs.select("zone_id", "v").groupBy("zone_id").transformWithStateInPandas(
        ZoneAccumulator(ttl_ms), "zone_id bigint, cnt bigint, sum_v bigint, min_v bigint, max_v bigint", "Update", "processingTime" if ttl_ms else "none"
    )


def to_table(stream: DataFrame, name: str, checkpoint: str, mode: str = "append"):
    """Run until all files are read, into a memory table."""
    return stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def to_batches(stream: DataFrame, each, checkpoint: str, mode: str = "update"):
    """Hand every micro-batch to ``each(df, batch_id)``."""
    return stream.writeStream.foreachBatch(each).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
