"""Splits: (chunk, file, range of tiles) from footers alone, and their expansion to work units."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.arith import floor_div
from ..functions.grid import GridMeta


def tile_files(meta: GridMeta, tiles: DataFrame | None = None) -> DataFrame | None:
    """file_id, tile_id pairs of a raster in many files; None stands for one file."""
    return None if tiles is None else tiles.select("file_id", "tile_id").distinct()


def plan(footer: DataFrame, meta: GridMeta, tiles_per_split: int = 64, files: DataFrame | None = None, one_file: bool = True, mode: str = "islands") -> DataFrame:
    """split_id, chunk_id, file_id, tile_lo, tile_hi, est_pixels; tiles without runs make no split.

    'islands': consecutive touched tiles, ``tiles_per_split`` of them at most; 'blocks': fixed
    ranges of tile numbers. ``one_file`` keeps a split inside one raster file.
    """
    touched = footer.select("chunk_id", "tile_id")
    if files is not None and one_file:
        touched = touched.join(files, "tile_id")
    else:
        touched = touched.withColumn("file_id", F.lit(0))
    key = ["chunk_id", "file_id"]
    if mode == "islands":
        w = Window.partitionBy(*key).orderBy("tile_id")
        first = F.when(F.col("tile_id") - F.lag("tile_id").over(w) == 1, 0).otherwise(1)
        t = touched.withColumn("__new", first)
        t = t.withColumn("__island", F.sum("__new").over(w))
        inside = Window.partitionBy(*key, "__island").orderBy("tile_id")
        t = t.withColumn("__part", floor_div((F.row_number().over(inside) - 1).cast("long"), tiles_per_split))
        group = [*key, "__island", "__part"]
    else:
        t = touched.withColumn("__part", floor_div(F.col("tile_id"), tiles_per_split))
        group = [*key, "__part"]
    out = t.groupBy(*group).agg(F.min("tile_id").alias("tile_lo"), F.max("tile_id").alias("tile_hi"), F.count(F.lit(1)).alias("n_tiles"))
    number = F.row_number().over(Window.partitionBy(*key).orderBy("tile_lo"))
    return out.select(
        F.concat_ws("-", *key, (number - 1).cast("string")).alias("split_id"), *key, "tile_lo", "tile_hi",
        (F.col("n_tiles") * meta.tile_w * meta.tile_h).cast("long").alias("est_pixels"),
    )


def expand(split: DataFrame, footer: DataFrame) -> DataFrame:
    """Work units: split_id, chunk_id, file_id, tile_id for each touched tile of a split."""
    every = split.select("split_id", "chunk_id", "file_id", F.explode(F.sequence("tile_lo", "tile_hi")).alias("tile_id"))
    return every.join(footer.select("chunk_id", "tile_id"), ["chunk_id", "tile_id"], "left_semi").select("split_id", "chunk_id", "file_id", "tile_id")


def balance(split: DataFrame) -> DataFrame:
    """One row: number of splits, largest and mean estimated pixels, their ratio."""
    return split.agg(F.count(F.lit(1)).alias("splits"), F.max("est_pixels").alias("largest"), F.avg("est_pixels").alias("mean"), (F.max("est_pixels") / F.avg("est_pixels")).alias("imbalance"))
