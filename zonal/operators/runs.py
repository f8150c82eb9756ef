"""Crossings of raster rows with zone edges, and runs of pixels between them.

Only raster metadata is needed here, no pixel. A scan line goes through the centres of a
row's pixels. All arithmetic is on whole numbers, so ties fall alike in every engine.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.arith import ceil_div, floor_div, long
from ..functions.grid import SNAP, GridMeta, tile_id
from .zones import ZoneLayer, edges

HALF = SNAP // 2


def edge_crossings(edge: DataFrame, meta: GridMeta, clip_rows: bool = True, turned: bool = False) -> DataFrame:
    """zone columns, y, x: x is the first pixel whose centre is at or right of the crossing.

    A centre on an edge counts as moved right by a little, and up by much less. ``turned``
    edges have x and y exchanged: there the move lies along the edge's own scan line, so a
    centre on a rising edge is before it, on any other edge behind it.
    """
    lo, hi = ceil_div(F.col("ya") - HALF, SNAP), ceil_div(F.col("yb") - HALF, SNAP)
    if clip_rows:
        lo, hi = F.greatest(lo, long(0)), F.least(hi, long(meta.rows))
    keep = [c for c in edge.columns if c not in ("xa", "ya", "xb", "yb")]
    spans = edge.withColumn("__lo", lo).withColumn("__hi", hi).where("__lo < __hi")
    rows = spans.withColumn("y", F.explode(F.sequence(F.col("__lo"), F.col("__hi") - 1)))
    d = F.col("yb") - F.col("ya")
    n = F.col("xa") * d + (F.col("y") * SNAP + HALF - F.col("ya")) * (F.col("xb") - F.col("xa"))
    x = ceil_div(n - d * HALF, d * SNAP)
    if turned:
        x = F.when(F.col("xb") > F.col("xa"), floor_div(n - d * HALF, d * SNAP) + 1).otherwise(x)
    return rows.select(*keep, "y", x.alias("x"))


def merge_order(rows: DataFrame, meta: GridMeta | None, x: str = "x0", tiles: int = 1024) -> DataFrame:
    """Runs or crossings (``x`` names their column) sorted as the raster is stored: by chunk,
    tile, row, zone and column. A chunk is dealt to tasks by ranges of ``tiles`` tiles."""
    if "tile_id" not in rows.columns:
        rows = rows.withColumn("tile_id", tile_id(meta, F.col(x), F.col("y")))
    return rows.repartition("chunk_id", floor_div(F.col("tile_id"), tiles)).sortWithinPartitions("chunk_id", "tile_id", "y", "zone_id", x)


def pair(crossings: DataFrame, meta: GridMeta) -> DataFrame:
    """Runs [x0, x1) between odd and even crossings of a zone's row, clipped after pairing."""
    group = [c for c in crossings.columns if c not in ("y", "x")]
    w = Window.partitionBy(*group, "y").orderBy("x")
    both = crossings.withColumn("__n", F.row_number().over(w)).withColumn("__next", F.lead("x").over(w))
    odd = both.where(F.col("__n") % 2 == 1)
    return odd.select(*group, "y", F.greatest("x", long(0)).alias("x0"), F.least("__next", long(meta.cols)).alias("x1")).where("x0 < x1")


def cut(runs: DataFrame, meta: GridMeta) -> DataFrame:
    """Runs cut at tile borders, with the tile of each piece: interior tiles are never lost."""
    rest = [c for c in runs.columns if c not in ("x0", "x1")]
    col = F.explode(F.sequence(floor_div(F.col("x0"), meta.tile_w), floor_div(F.col("x1") - 1, meta.tile_w)))
    pieces = runs.withColumn("__c", col)
    x0, x1 = F.greatest(F.col("x0"), F.col("__c") * meta.tile_w), F.least(F.col("x1"), (F.col("__c") + 1) * meta.tile_w)
    return pieces.select(*rest, x0.alias("x0"), x1.alias("x1")).withColumn("tile_id", tile_id(meta, F.col("x0"), F.col("y")))


def zone_runs(layer: ZoneLayer | DataFrame, meta: GridMeta, keep: tuple[str, ...] = ()) -> DataFrame:
    """keep.., zone_id, y, x0, x1 for all zones. Column-major rasters swap x and y of the
    edges, so that runs follow columns; they come back as runs along y under the same names."""
    e = edges(layer, keep)
    if meta.order == "row":
        return pair(edge_crossings(e, meta), meta)
    turned = turn(layer, keep)
    return pair(edge_crossings(turned, transposed(meta), turned=True), transposed(meta))


def transposed(meta: GridMeta) -> GridMeta:
    """The same raster with x and y exchanged: a column-major one becomes row-major."""
    return GridMeta(meta.cols, meta.rows, meta.tile_h, meta.tile_w, order="row", nodata=meta.nodata, n_files=meta.n_files)


def turn(layer: ZoneLayer | DataFrame, keep: tuple[str, ...] = ()) -> DataFrame:
    """Edges with x and y exchanged."""
    df = layer.df if isinstance(layer, ZoneLayer) else layer
    swap = F.transform("rings", lambda r: F.transform(r, lambda p: F.struct(p["gy"].alias("gx"), p["gx"].alias("gy"))))
    return edges(df.select("zone_id", *keep, swap.alias("rings")), keep)
