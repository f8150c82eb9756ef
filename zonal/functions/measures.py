"""Measures of runs of the methods: counts, sizes, times, rank correlation, balance."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators import baselines, splits, store
from ..operators import merge_ordered as mo
from ..operators import runs as R
from ..operators import zones
from ..operators.zones import ChunkSpec, ZoneLayer
from .grid import RasterLayer


def collect(raster: RasterLayer, layer: ZoneLayer, spec: ChunkSpec = ChunkSpec(), partitioner: str = "none", tiles_per_split: int = 64) -> DataFrame:
    """One row of measured counterparts of the cost model: crossings, runs, pieces, units,
    splits, distinct tiles, tiles and pixels read by merge-ordered and by clip."""
    meta = raster.meta
    turned = meta if meta.order == "row" else R.transposed(meta)
    e = zones.edges(layer) if meta.order == "row" else R.turn(layer)
    pieces = mo.intersect(layer, meta, spec, partitioner)
    foot = store.footer(pieces).persist()  # read twice below, one row a touched tile
    area = meta.tile_w * meta.tile_h
    crossings = R.edge_crossings(e, turned).agg(F.count(F.lit(1)).alias("crossings"))
    runs = R.zone_runs(layer, meta).agg(F.count(F.lit(1)).alias("runs"), F.coalesce(F.sum(F.col("x1") - F.col("x0")), F.lit(0)).alias("covered_pixels"))
    feet = foot.agg(F.count(F.lit(1)).alias("units"), F.countDistinct("tile_id").alias("distinct_tiles"), F.coalesce(F.sum("n_runs"), F.lit(0)).alias("pieces"))
    parts = splits.plan(foot, meta, tiles_per_split).agg(F.count(F.lit(1)).alias("splits"))
    clip = baselines.overlapped_tiles(layer, meta).agg(F.count(F.lit(1)).alias("clip_tiles"))
    one = crossings.join(runs).join(feet).join(parts).join(clip)  # single rows side by side
    return one.withColumn("merge_pixels", F.col("units") * area).withColumn("clip_pixels", F.col("clip_tiles") * area)


def tile_reads(layer: ZoneLayer, raster: RasterLayer, spec: ChunkSpec, partitioner: str = "none") -> DataFrame:
    """One row: tiles read by chunks."""
    return store.footer(mo.intersect(layer, raster.meta, spec, partitioner)).agg(F.count(F.lit(1)).alias("tile_reads"))


def spearman(df: DataFrame, x: str, y: str, ties: str = "average", by: tuple[str, ...] = ()) -> DataFrame:
    """Rank correlation of two columns, per group of ``by``. 'average': ties share the mean of
    their ranks; 'order': ties rank in order of the column ``row``."""

    def ranked(d: DataFrame, c: str) -> DataFrame:
        if ties == "order":
            return d.withColumn(f"__r_{c}", F.row_number().over(Window.partitionBy(*by).orderBy(c, "row")).cast("double"))
        first = F.rank().over(Window.partitionBy(*by).orderBy(c))
        same = F.count(F.lit(1)).over(Window.partitionBy(*by, c))
        return d.withColumn(f"__r_{c}", first + (same - 1) / 2.0)

    both = ranked(ranked(df.where(F.col(x).isNotNull() & F.col(y).isNotNull()), x), y)
    return both.groupBy(*by).agg(F.corr(f"__r_{x}", f"__r_{y}").alias("r_s"))


def pearson(df: DataFrame, x: str, y: str, by: tuple[str, ...] = ()) -> DataFrame:
    """Correlation of the values: near 1 whenever both axes grow exponentially, so misleading."""
    return df.groupBy(*by).agg(F.corr(x, y).alias("r"))


def normalize(df: DataFrame, value: str, series: str) -> DataFrame:
    """Each series divided by its largest value, for comparing trends."""
    return df.withColumn(f"{value}_normalized", F.col(value) / F.max(value).over(Window.partitionBy(series)))


def compression_ratio(raw_bytes: float, compressed_bytes: float) -> float:
    return raw_bytes / compressed_bytes


def speedup(seconds_without: float, seconds_with: float) -> float:
    return seconds_without / seconds_with


def timed(action: Callable[[], object]) -> tuple[float, object]:
    """Seconds from reading both inputs to the answer, and the action's value."""
    began = time.perf_counter()
    value = action()
    return time.perf_counter() - began, value


def repeat(action: Callable[[], object], n: int = 3) -> float:
    """Mean seconds of n runs."""
    return sum(timed(action)[0] for _ in range(n)) / n


def ingest(write: Callable[[], object] | None) -> float:
    """Seconds of a loading step; in-place processing has none."""
    return timed(write)[0] if write else 0.0


def store_sizes(raster: RasterLayer, layer: ZoneLayer, base: str, codecs: tuple[str, ...] = ("none", "gzip", "snappy")) -> dict[str, int]:
    """Bytes of the crossing store by codec, dictionaries off."""
    runs = mo.intersect(layer, raster.meta)
    out = {}
    for codec in codecs:
        store.write(runs, f"{base}/{codec}", codec, plain=True, meta=raster.meta)
        out[codec] = store.stored_bytes(runs.sparkSession, f"{base}/{codec}/runs")
    return out
