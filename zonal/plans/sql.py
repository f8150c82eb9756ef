"""SQL surface: views of layers and runs, SQL functions, and table functions."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..functions.grid import GridMeta, RasterLayer
from ..operators import merge_ordered as mo
from ..operators.zones import ChunkSpec, ZoneLayer


def register_functions(spark: SparkSession, meta: GridMeta) -> None:
    """zonal_tile_id(x, y), zonal_lon(x) and zonal_lat(y) for one grid."""
    tx, ty = f"floor(x / {meta.tile_w})", f"floor(y / {meta.tile_h})"
    tile = f"{ty} * {meta.tiles_x} + {tx}" if meta.order == "row" else f"{tx} * {meta.tiles_y} + {ty}"
    spark.sql(f"create or replace temporary function zonal_tile_id(x bigint, y bigint) returns bigint return cast({tile} as bigint)")
    spark.sql(f"create or replace temporary function zonal_lon(x bigint) returns double return {meta.x0}D + (x + 0.5D) * {meta.px}D")
    spark.sql(f"create or replace temporary function zonal_lat(y bigint) returns double return {meta.y0}D + (y + 0.5D) * {meta.py}D")


def register_views(spark: SparkSession, raster: RasterLayer, zones: ZoneLayer, prefix: str = "zonal") -> None:
    """Views <prefix>_raster, <prefix>_zones and <prefix>_runs, and the functions above."""
    register_functions(spark, raster.meta)
    raster.df.createOrReplaceTempView(f"{prefix}_raster")
    zones.df.createOrReplaceTempView(f"{prefix}_zones")
    mo.intersect(zones, raster.meta, ChunkSpec("none")).createOrReplaceTempView(f"{prefix}_runs")


@udtf(returnType="x: bigint, y: bigint, v: bigint")
class RunPixels:
    """The pixels of a run as rows: run_pixels(y, x0, x1, values of that row)."""

    def eval(self, y: int, x0: int, x1: int, values: list) -> Iterator[tuple]:
        for x in range(x0, x1):
            if values[x - x0] is not None:
                yield x, y, values[x - x0]


def register_table_functions(spark: SparkSession) -> None:
    spark.udtf.register("zonal_run_pixels", RunPixels)


def grouped_udaf(pairs: DataFrame, fold: Callable[[pd.Series], float], name: str = "value") -> DataFrame:
    """A Series-to-scalar aggregate per zone. It holds a whole zone and has no partial phase,
    so it is for small zones; ``accumulate_custom`` has both."""

    @F.pandas_udf("double")
    def run(v: pd.Series) -> float:
        return float(fold(v))

    return pairs.groupBy("zone_id").agg(run(F.col("v").cast("double")).alias(name))
