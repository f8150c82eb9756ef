"""Raster layers: metadata, coordinates, tiles.

A raster is a matrix of measurements. It comes as pixels (one row each), which relational
tables give, or as tiles (one row a tile, its values in one array), which files give.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .arith import floor_div, long

#: Lattice units a pixel: vertices are snapped to sixteenths of a pixel.
SNAP = 16


@dataclass(frozen=True)
class GridMeta:
    """A few numbers that describe a raster; everything before pixel access needs only these."""

    rows: int
    cols: int
    tile_w: int = 16
    tile_h: int = 16
    x0: float = -180.0
    y0: float = 90.0
    px: float = 0.25
    py: float = -0.25
    order: str = "row"  # numbering of tiles and storage inside them: 'row' or 'col'
    nodata: int | None = None
    n_files: int = 1

    @property
    def tiles_x(self) -> int:
        return -(-self.cols // self.tile_w)

    @property
    def tiles_y(self) -> int:
        return -(-self.rows // self.tile_h)

    @property
    def pixels(self) -> int:
        return self.rows * self.cols

    def with_tiles(self, w: int, h: int, order: str | None = None) -> GridMeta:
        return replace(self, tile_w=w, tile_h=h, order=order or self.order)


@dataclass(frozen=True)
class RasterLayer:
    """``form`` 'pixels': x, y, v [, file_id]; 'tiles': file_id, tile_id, values.

    A written tile table also knows its path and how many tiles a directory (``tile_group``) holds.
    """

    df: DataFrame
    meta: GridMeta
    form: str = "pixels"
    path: str | None = None
    tiles_per_group: int | None = None


def side_lengths(n: int) -> tuple[int, int]:
    """(columns, rows) of the near-square grid that holds keys 0 .. n - 1."""
    w = math.isqrt(n - 1) + 1 if n else 0
    return w, (-(-n // w) if w else 0)


def from_key(df: DataFrame, key: str, value: Column, tile: tuple[int, int] = (16, 16), extra: tuple[Column, ...] = ()) -> RasterLayer:
    """A raster from a table with gap-free keys: one count is the only driver round trip."""
    w, h = side_lengths(df.count())
    k = F.col(key).cast("long")
    pixels = df.select(F.pmod(k, long(max(w, 1))).alias("x"), floor_div(k, max(w, 1)).alias("y"), value.alias("v"), *extra)
    return RasterLayer(pixels, GridMeta(h, w, *tile))


def from_matrix(df: DataFrame, row: str, values: str, scale: int, tile_h: int = 1) -> RasterLayer:
    """Rows of vectors as a raster: one row a table row, one column an element."""
    shape = df.agg(F.max(row), F.max(F.size(values))).first()
    meta = GridMeta(int(shape[0] if shape[0] is not None else -1) + 1, int(shape[1] or 0), int(shape[1] or 1), tile_h)
    pixels = df.select(F.col(row).cast("long").alias("y"), F.posexplode(values).alias("x", "e"))
    return RasterLayer(pixels.select(F.col("x").cast("long").alias("x"), "y", F.round(F.col("e").cast("double") * scale).cast("long").alias("v")), meta)


def from_cells(df: DataFrame, x: str, y: str, value: Column, tile: tuple[int, int]) -> RasterLayer:
    """A sparse raster: rows that fall into one cell are summed."""
    size = df.agg(F.max(x), F.max(y)).first()
    cells = df.groupBy(F.col(x).cast("long").alias("x"), F.col(y).cast("long").alias("y")).agg(F.sum(value).cast("long").alias("v"))
    return RasterLayer(cells, GridMeta(int(size[1] if size[1] is not None else -1) + 1, int(size[0] if size[0] is not None else -1) + 1, *tile))


# ---- coordinates


def world_to_grid(meta: GridMeta, lon: Column, lat: Column) -> tuple[Column, Column]:
    return F.floor((lon - meta.x0) / meta.px).cast("long"), F.floor((lat - meta.y0) / meta.py).cast("long")


def world_to_lattice(meta: GridMeta, lon: Column, lat: Column) -> tuple[Column, Column]:
    """Snapped lattice coordinates of a vertex."""
    return F.round((lon - meta.x0) / meta.px * SNAP).cast("long"), F.round((lat - meta.y0) / meta.py * SNAP).cast("long")


def grid_to_world(meta: GridMeta, x: Column, y: Column) -> tuple[Column, Column]:
    """Longitude and latitude of a pixel's centre."""
    return meta.x0 + (x + 0.5) * meta.px, meta.y0 + (y + 0.5) * meta.py


# ---- tiles


def tile_id(meta: GridMeta, x: Column, y: Column) -> Column:
    tx, ty = floor_div(x, meta.tile_w), floor_div(y, meta.tile_h)
    return ty * long(meta.tiles_x) + tx if meta.order == "row" else tx * long(meta.tiles_y) + ty


def tile_place(meta: GridMeta, tile: Column) -> tuple[Column, Column]:
    """(tile row, tile column) of a tile id."""
    n = long(max(meta.tiles_x if meta.order == "row" else meta.tiles_y, 1))
    major, minor = floor_div(tile, n), F.pmod(tile, n)
    return (major, minor) if meta.order == "row" else (minor, major)


def tile_bounds(meta: GridMeta, tile: Column) -> Column:
    """First and last-but-one pixel coordinates of a tile: struct<x0, y0, x1, y1>."""
    r, c = tile_place(meta, tile)
    return F.struct(
        (c * meta.tile_w).alias("x0"), (r * meta.tile_h).alias("y0"),
        F.least((c + 1) * meta.tile_w, long(meta.cols)).alias("x1"), F.least((r + 1) * meta.tile_h, long(meta.rows)).alias("y1"),
    )


#: Tiles up to this many cells are filled by a map in the plan; larger ones by arrays in Arrow.
MAP_CELLS = 4096


def tile_pixels(layer: RasterLayer) -> RasterLayer:
    """Pixels to tiles: one exchange. Missing pixels become nulls at their positions."""
    meta = layer.meta
    w, h = meta.tile_w, meta.tile_h
    file_id = F.col("file_id") if "file_id" in layer.df.columns else F.lit(0)
    lx, ly = F.pmod("x", long(w)), F.pmod("y", long(h))
    pos = ly * w + lx if meta.order == "row" else lx * h + ly
    px = layer.df.select(file_id.cast("int").alias("file_id"), tile_id(meta, F.col("x"), F.col("y")).alias("tile_id"), F.struct(pos.cast("int").alias("p"), "v").alias("pv"))
    packed = px.groupBy("file_id", "tile_id").agg(F.sort_array(F.collect_list("pv")).alias("pvs"))
    if w * h <= MAP_CELLS:
        filled = F.transform(F.sequence(F.lit(0), F.lit(w * h - 1)), lambda p: F.try_element_at(F.map_from_entries("pvs"), p))
        values = F.when(F.size("pvs") == w * h, F.transform("pvs", lambda s: s["v"])).otherwise(filled)
        tiles = packed.select("file_id", "tile_id", values.alias("values"))
    else:
        kind = layer.df.schema["v"].dataType.simpleString()
        tiles = packed.select("file_id", "tile_id", "pvs.p", "pvs.v").mapInArrow(_filler(w * h), f"file_id int, tile_id bigint, values array<{kind}>")
    return RasterLayer(tiles, meta, "tiles")


def _filler(cells: int):
    def run(batches: Iterator) -> Iterator:
        import numpy as np
        import pyarrow as pa

        for b in batches:
            p, v = b.column(2), b.column(3)
            at = np.repeat(np.arange(b.num_rows), np.diff(p.offsets.to_numpy())) * cells + p.flatten().to_numpy()
            flat = v.flatten()
            take = np.full(b.num_rows * cells, -1, np.int64)
            take[at] = np.arange(len(at))
            values = flat.take(pa.array(take, mask=take < 0))
            offsets = pa.array(np.arange(b.num_rows + 1, dtype=np.int32) * cells)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.ListArray.from_arrays(offsets, values)], ["file_id", "tile_id", "values"])

    return run


def explode_tiles(layer: RasterLayer) -> DataFrame:
    """Tiles back to pixels x, y, v; nulls (nodata) are left out."""
    meta = layer.meta
    w, h = meta.tile_w, meta.tile_h
    r, c = tile_place(meta, F.col("tile_id"))
    out = layer.df.select("file_id", r.alias("r"), c.alias("c"), F.posexplode("values").alias("p", "v")).where("v is not null")
    lx, ly = (F.pmod("p", F.lit(w)), F.floor(F.col("p") / w)) if meta.order == "row" else (F.floor(F.col("p") / h), F.pmod("p", F.lit(h)))
    return out.select((F.col("c") * w + lx).cast("long").alias("x"), (F.col("r") * h + ly).cast("long").alias("y"), "v", "file_id")


def strips(layer: RasterLayer) -> DataFrame:
    """One row per raster row of a tile (column of a column-major one): file_id, tile_id, y,
    x_off, values. Narrow; only array slices are made."""
    meta = layer.meta
    w, h = (meta.tile_w, meta.tile_h) if meta.order == "row" else (meta.tile_h, meta.tile_w)
    r, c = tile_place(meta, F.col("tile_id"))
    if meta.order != "row":
        r, c = c, r
    line = layer.df.select("file_id", "tile_id", r.alias("r"), c.alias("c"), "values", F.explode(F.sequence(F.lit(0), F.lit(h - 1))).alias("i"))
    return line.select(
        "file_id", "tile_id", (F.col("r") * h + F.col("i")).cast("long").alias("y"), (F.col("c") * w).cast("long").alias("x_off"),
        F.slice("values", F.col("i") * w + 1, F.lit(w)).alias("values"),
    )


def blank(layer: RasterLayer, nodata) -> RasterLayer:
    """Values equal to ``nodata`` become null; aggregates then skip them."""
    if layer.form == "pixels":
        return replace(layer, df=layer.df.withColumn("v", F.nullif("v", F.lit(nodata))).where("v is not null"))
    return replace(layer, df=layer.df.withColumn("values", F.transform("values", lambda v: F.nullif(v, F.lit(nodata)))))
