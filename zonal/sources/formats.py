"""Zone and raster formats: WKT, WKB, GeoJSON, CSV and tile tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.grid import SNAP, GridMeta, RasterLayer
from ..operators.zones import ZoneLayer, from_rings


def _ring(text: Column, meta: GridMeta | None) -> Column:
    """'x y, x y, ...' to lattice points; world coordinates if ``meta`` is given."""

    def point(p: Column) -> Column:
        xy = F.split(F.trim(p), r"\s+")
        x, y = xy[0].cast("double"), xy[1].cast("double")
        if meta is not None:
            x, y = (x - meta.x0) / meta.px * SNAP, (y - meta.y0) / meta.py * SNAP
        return F.struct(F.round(x).cast("long").alias("gx"), F.round(y).cast("long").alias("gy"))

    return F.transform(F.split(text, ","), point)


def from_wkt(df: DataFrame, zone_id: str, wkt: str, meta: GridMeta | None = None) -> ZoneLayer:
    """POLYGON and MULTIPOLYGON texts; every bracketed list of points is a ring."""
    found = F.regexp_extract_all(F.col(wkt), F.lit(r"\(([^()]+)\)"), F.lit(1))
    return from_rings(df, zone_id, F.transform(found, lambda r: _ring(r, meta)))


def to_wkt(layer: ZoneLayer) -> DataFrame:
    """zone_id, wkt in lattice coordinates, rings closed."""
    pt = lambda p: F.concat_ws(" ", p["gx"].cast("string"), p["gy"].cast("string"))
    ring = lambda r: F.concat(F.lit("("), F.array_join(F.transform(F.concat(r, F.slice(r, 1, 1)), pt), ", "), F.lit(")"))
    return layer.df.select("zone_id", F.concat(F.lit("POLYGON ("), F.array_join(F.transform("rings", ring), ", "), F.lit(")")).alias("wkt"))


def from_geojson(df: DataFrame, zone_id: str, geometry: str, meta: GridMeta | None = None) -> ZoneLayer:
    """Polygon geometries as JSON texts."""
    coords = F.from_json(F.col(geometry), "coordinates array<array<array<double>>>")["coordinates"]

    def point(p: Column) -> Column:
        x, y = p[0], p[1]
        if meta is not None:
            x, y = (x - meta.x0) / meta.px * SNAP, (y - meta.y0) / meta.py * SNAP
        return F.struct(F.round(x).cast("long").alias("gx"), F.round(y).cast("long").alias("gy"))

    return from_rings(df, zone_id, F.transform(coords, lambda r: F.transform(r, point)))


def to_wkb(layer: ZoneLayer) -> DataFrame:
    """zone_id, wkb (little-endian polygons, lattice coordinates as doubles)."""

    def run(batches):
        import struct

        import pyarrow as pa

        for b in batches:
            out = []
            for rings in b.column(1).to_pylist():
                body = struct.pack("<BII", 1, 3, len(rings))
                for r in rings:
                    closed = [*r, *r[:1]]
                    body += struct.pack("<I", len(closed)) + b"".join(struct.pack("<dd", p["gx"], p["gy"]) for p in closed)
                out.append(body)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.binary())], ["zone_id", "wkb"])

    return layer.df.select("zone_id", "rings").mapInArrow(run, "zone_id bigint, wkb binary")


def from_wkb(df: DataFrame, zone_id: str, wkb: str) -> ZoneLayer:
    """Polygons in WKB of either byte order."""

    def run(batches):
        import struct

        import pyarrow as pa

        kind = pa.list_(pa.list_(pa.struct([("gx", pa.int64()), ("gy", pa.int64())])))
        for b in batches:
            out = []
            for raw in b.column(1).to_pylist():
                end = "<" if raw[0] else ">"
                (n,), at, rings = struct.unpack_from(f"{end}I", raw, 5), 9, []
                for _ in range(n):
                    (m,) = struct.unpack_from(f"{end}I", raw, at)
                    flat = struct.unpack_from(f"{end}{2 * m}d", raw, at + 4)
                    at += 4 + 16 * m
                    pts = [{"gx": round(flat[2 * i]), "gy": round(flat[2 * i + 1])} for i in range(m)]
                    rings.append(pts[:-1] if len(pts) > 1 and pts[0] == pts[-1] else pts)
                out.append(rings)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, kind)], ["zone_id", "rings"])

    made = df.select(F.col(zone_id).cast("long").alias("zone_id"), F.col(wkb).cast("binary").alias("wkb")).mapInArrow(run, "zone_id bigint, rings array<array<struct<gx:bigint,gy:bigint>>>")
    return ZoneLayer(made)


def write_tiles(layer: RasterLayer, path: str, tiles_per_group: int = 1024, codec: str = "snappy") -> None:
    """A tile table in directories of neighbouring tiles, sorted, so tile ranges prune."""
    df = layer.df.withColumn("tile_group", F.floor(F.col("tile_id") / tiles_per_group))
    df.repartition("file_id", "tile_group").sortWithinPartitions("tile_group", "tile_id").write.option("compression", codec).partitionBy("tile_group").parquet(path)


def read_tiles(spark: SparkSession, path: str, meta: GridMeta, tiles_per_group: int | None = None) -> RasterLayer:
    """``tiles_per_group`` as the table was written with: directories without a run are then skipped."""
    return RasterLayer(spark.read.parquet(path), meta, "tiles", path, tiles_per_group)


def write_bucketed(layer: RasterLayer, name: str, buckets: int | None = None, path: str | None = None) -> RasterLayer:
    """A catalog table bucketed and sorted by tile: work units come to its buckets, no tile moves.

    There are at least as many buckets as shuffle partitions; with fewer Spark would rather
    exchange both sides.
    """
    spark = layer.df.sparkSession
    buckets = buckets or max(64, int(spark.conf.get("spark.sql.shuffle.partitions")))
    writer = layer.df.repartition(buckets, "tile_id").write.bucketBy(buckets, "tile_id").sortBy("tile_id")
    (writer.option("path", path) if path else writer).saveAsTable(name)
    return RasterLayer(spark.table(name), layer.meta, "tiles")


def write_table(df: DataFrame, path: str, kind: str = "parquet") -> None:
    """Any result to Parquet, ORC, JSON, CSV (with a header) or text; columns that a format has
    no type for become JSON strings."""
    if kind in ("csv", "text"):
        flat = [F.to_json(c).alias(c) if t.startswith(("array", "map", "struct")) else F.col(c) for c, t in df.dtypes]
        df = df.select(*flat)
    if kind == "text":
        df = df.select(F.to_json(F.struct(*df.columns)).alias("value"))
    if kind not in ("parquet", "orc", "json", "csv", "text"):
        raise ValueError(f"unknown format {kind!r}")
    writer = df.write.option("header", "true") if kind == "csv" else df.write
    writer.format(kind).save(path)


#: A tiled binary raster begins with these eight bytes; whole numbers follow, all little-endian:
#: columns, rows, tile width, tile height as 32-bit, then the kind of values as 32-bit. Tiles
#: follow in row-major order, each width x height values, those outside the raster too.
BINARY_MAGIC = b"ZTILES01"
BINARY_KINDS = {1: ("<i2", "smallint"), 2: ("<i4", "int"), 3: ("<i8", "bigint"), 4: ("<f4", "float"), 5: ("<f8", "double")}
_HEADER = 28


def to_tiled_binary(columns: int, rows: int, tile_w: int, tile_h: int, kind: int, tiles: list) -> bytes:
    """The bytes of a small tiled raster; ``tiles`` are arrays in row-major order."""
    import struct

    import numpy as np

    body = b"".join(np.asarray(t, BINARY_KINDS[kind][0]).tobytes() for t in tiles)
    return BINARY_MAGIC + struct.pack("<5I", columns, rows, tile_w, tile_h, kind) + body


def read_tiled_binary(spark: SparkSession, path: str, nodata: float | None = None) -> RasterLayer:
    """Tiled binary files of one shape: a file is one ``file_id``, its tiles one row each.

    Spark reads the files, so any storage it knows works; a file is held by one task, so a
    large raster comes as many files (bands of tile rows would each be a layer of their own).
    The shape is read from the first file's header.
    """
    import struct

    files = spark.read.format("binaryFile").load(path).select("path", "content")
    head = files.select(F.substring("content", 1, _HEADER).alias("h")).first()
    if head is None or bytes(head["h"][:8]) != BINARY_MAGIC:
        raise ValueError(f"no tiled raster at {path}")
    w, h, tile_w, tile_h, kind = struct.unpack("<5I", bytes(head["h"][8:_HEADER]))
    dtype, name = BINARY_KINDS[kind]
    meta = GridMeta(h, w, tile_w, tile_h)
    names = [r[0] for r in files.select("path").orderBy("path").collect()]
    numbers = {p: i for i, p in enumerate(names)}

    def run(batches):
        import numpy as np
        import pyarrow as pa

        cells = tile_w * tile_h
        for b in batches:
            for where, raw in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                raw = raw.as_buffer()
                if raw[:_HEADER].to_pybytes() != BINARY_MAGIC + struct.pack("<5I", w, h, tile_w, tile_h, kind):
                    raise ValueError(f"{where} has another shape")
                values = np.frombuffer(raw, dtype, offset=_HEADER).reshape(-1, cells)
                for t in range(0, len(values), 1024):
                    part = values[t : t + 1024]
                    ids = np.arange(t, t + len(part), dtype=np.int64)
                    x = ids[:, None] % meta.tiles_x * tile_w + np.arange(cells) % tile_w
                    y = ids[:, None] // meta.tiles_x * tile_h + np.arange(cells) // tile_w
                    none = (x >= w) | (y >= h) | (np.zeros(part.shape, bool) if nodata is None else part == nodata)
                    lists = pa.ListArray.from_arrays(np.arange(0, part.size + 1, cells, dtype=np.int32), pa.array(part.reshape(-1), mask=none.reshape(-1)))
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part), numbers[where], np.int32)), pa.array(ids), lists], ["file_id", "tile_id", "values"])

    return RasterLayer(files.mapInArrow(run, f"file_id int, tile_id bigint, values array<{name}>"), meta, "tiles")
