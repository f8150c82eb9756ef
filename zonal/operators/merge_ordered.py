"""The merge-ordered method: sort the vector side into the raster's order, read tiles once.

Intersection works on metadata, selection reads every touched tile once a chunk beside the
chunk's runs in the tile's own order, aggregation is partial and final. Tiles stay where they
are as long as runs are broadcast, the tile table is bucketed by tile, or splits are read from
a written tile table ('splits'). Pixels that are loose rows of a table have no order to
exploit: where their runs are too many to broadcast, both sides are exchanged by tile.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.accumulate import DEFAULT, keep_empty, merge_partials, value_aggs
from ..functions.grid import GridMeta, RasterLayer, tile_id
from . import runs as R
from . import selection, store, zones
from .zones import ChunkSpec, ZoneLayer

#: Aggregates that run partials can express.
BY_RUNS = {"count", "sum", "min", "max", "avg"}


def chunked(layer: ZoneLayer, spec: ChunkSpec, partitioner: str = "none") -> DataFrame:
    df = zones.with_mbr(layer)
    if spec.by == "polygons" and partitioner != "none":
        return zones.partition_spatial(df, partitioner, spec.size)
    return zones.chunk(df, spec)


def intersect(layer: ZoneLayer, meta: GridMeta, spec: ChunkSpec = ChunkSpec(), partitioner: str = "none") -> DataFrame:
    """chunk_id, zone_id, tile_id, y, x0, x1: all runs, cut at tiles. Needs no pixel.

    A column-major raster gives runs along its columns: y then names the column.
    """
    return cut_runs(R.zone_runs(chunked(layer, spec, partitioner), meta, ("chunk_id",)), meta)


def cut_runs(runs: DataFrame, meta: GridMeta) -> DataFrame:
    return R.cut(runs, meta if meta.order == "row" else R.transposed(meta))


def selected(raster: RasterLayer, runs: DataFrame, strategy: str) -> DataFrame:
    """(zone_id, v) pairs of either form of raster."""
    if raster.form == "tiles":
        return selection.pairs(raster, runs, strategy)
    if raster.meta.order == "row":
        return selection.range_join(raster, runs, strategy)
    rest = [c for c in raster.df.columns if c not in ("x", "y")]
    turned = RasterLayer(raster.df.select(F.col("y").alias("x"), F.col("x").alias("y"), *rest), R.transposed(raster.meta))
    return selection.range_join(turned, runs, strategy)


def zonal(
    raster: RasterLayer,
    layer: ZoneLayer,
    aggs: tuple[str, ...] = DEFAULT,
    spec: ChunkSpec = ChunkSpec(),
    partitioner: str = "none",
    store_path: str | None = None,
    codec: str = "snappy",
    strategy: str = "auto",
    reduce: str = "hof",
    empty: bool = True,
    wide: bool = False,
    tiles_per_split: int = 64,
    one_file: bool = True,
) -> DataFrame:
    """zone_id and aggregates. 'splits' needs ``store_path`` and a raster read from a tile table."""
    strategy = selection.resolved(strategy, layer, raster.meta)
    runs = intersect(layer, raster.meta, spec, partitioner)
    if strategy == "splits":
        if raster.path is None or store_path is None:
            raise ValueError("splits are read from a written tile table and a crossing store")
        if raster.meta.order != "row" or not set(aggs) <= BY_RUNS:
            raise ValueError("splits give min, max, sum, count and avg of row-major tiles")
        from ..sources.split_source import zonal_from_store

        store.write(runs, store_path, codec)
        out = zonal_from_store(runs.sparkSession, raster, store_path, tiles_per_split, one_file, aggs, wide)
        return keep_empty(out, layer.df) if empty else out
    if store_path:
        store.write(runs, store_path, codec)
        runs = store.read(runs.sparkSession, store_path, raster.meta)
    runs = runs.select("chunk_id", "zone_id", "tile_id", "y", "x0", "x1")
    if raster.form == "tiles" and set(aggs) <= BY_RUNS and reduce != "pairs":
        out = merge_partials(selection.reduce_runs(raster, runs, reduce, strategy), ["zone_id"], aggs, wide)
    else:
        got = selected(raster, runs.drop("chunk_id") if raster.form == "pixels" else runs, strategy)
        out = got.groupBy("zone_id").agg(*value_aggs(aggs, got, wide=wide))
    return keep_empty(out, layer.df) if empty else out


def zonal_many(rasters: dict[str, RasterLayer], layer: ZoneLayer, aggs: tuple[str, ...] = DEFAULT, strategy: str = "auto") -> DataFrame:
    """Several layers or bands on one grid, such as a time series: runs are made once for all."""
    metas = {(r.meta.rows, r.meta.cols, r.meta.tile_w, r.meta.tile_h, r.meta.order) for r in rasters.values()}
    if len(metas) != 1:
        raise ValueError("the layers must share one grid")
    meta = next(iter(rasters.values())).meta
    stacked = None
    for name, r in rasters.items():
        px = r.df.select("x", "y", "v", F.lit(name).alias("layer"))
        stacked = px if stacked is None else stacked.unionByName(px)
    runs = intersect(layer, meta, ChunkSpec("none")).select("zone_id", "tile_id", "y", "x0", "x1")
    got = selection.range_join(RasterLayer(stacked, meta), runs, selection.resolved(strategy, layer, meta))
    return got.groupBy("layer", "zone_id").agg(*value_aggs(aggs, got))


def pixels_in_tiles(raster: RasterLayer) -> DataFrame:
    return raster.df.withColumn("tile_id", tile_id(raster.meta, F.col("x"), F.col("y")))
