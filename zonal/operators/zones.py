"""Zone layers: rings to edges, statistics, chunks and spatial partitions.

A zone is a list of rings on the lattice of sixteenths of a pixel. Even-odd rule: holes,
islands and parts of a multipolygon are just rings.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.arith import floor_div, hilbert, long, morton
from ..functions.grid import SNAP, GridMeta

RINGS = "array<array<struct<gx:bigint,gy:bigint>>>"


@dataclass(frozen=True)
class ZoneLayer:
    """zone_id, rings and any attributes."""

    df: DataFrame


def point(gx: Column | int, gy: Column | int) -> Column:
    return F.struct(long(gx).cast("long").alias("gx"), long(gy).cast("long").alias("gy"))


def from_rings(df: DataFrame, zone_id: str, rings: Column, *attributes: str) -> ZoneLayer:
    return ZoneLayer(df.select(F.col(zone_id).cast("long").alias("zone_id"), rings.cast(RINGS).alias("rings"), *attributes))


def from_template(df: DataFrame, zone_id: str, templates: list[list[tuple[int, int]]], scale: Column, cx: Column, cy: Column, *attributes: str) -> ZoneLayer:
    """Every zone is the template's rings, scaled and moved."""
    rings = F.array(*[F.array(*[point(cx + scale * dx, cy + scale * dy) for dx, dy in ring]) for ring in templates])
    return from_rings(df, zone_id, rings, *attributes)


def dissolve(layer: ZoneLayer, into: str) -> ZoneLayer:
    """Zones of one attribute value joined to a multipolygon; shared edges cancel by parity."""
    return ZoneLayer(layer.df.groupBy(F.col(into).cast("long").alias("zone_id")).agg(F.flatten(F.collect_list("rings")).alias("rings")))


def edges(layer: ZoneLayer | DataFrame, keep: tuple[str, ...] = ()) -> DataFrame:
    """zone_id, xa, ya, xb, yb with ya < yb; rings are closed, horizontal edges dropped."""
    df = layer.df if isinstance(layer, ZoneLayer) else layer
    ring = df.select("zone_id", *keep, F.explode("rings").alias("r")).where(F.size("r") > 1)
    closed = F.concat(F.slice("r", F.lit(2), F.size("r") - 1), F.slice("r", 1, 1))
    pairs = F.zip_with("r", closed, lambda a, b: F.struct(a.alias("a"), b.alias("b")))
    e = ring.select("zone_id", *keep, F.explode(pairs).alias("e")).select("zone_id", *keep, "e.a", "e.b").where("a.gy <> b.gy")
    up = F.col("a.gy") < F.col("b.gy")
    return e.select(
        "zone_id", *keep,
        *[F.when(up, F.col(f"{p}.{c}")).otherwise(F.col(f"{q}.{c}")).alias(n) for p, q, c, n in (("a", "b", "gx", "xa"), ("a", "b", "gy", "ya"), ("b", "a", "gx", "xb"), ("b", "a", "gy", "yb"))],
    )


def _extreme(rings: Column, f, field: str) -> Column:
    return f(F.transform(F.flatten(rings), lambda p: p[field]))


def with_mbr(layer: ZoneLayer) -> DataFrame:
    """Adds mbr struct<x0, y0, x1, y1> (lattice), n_edges and bytes; no exchange."""
    r = F.col("rings")
    mbr = F.struct(_extreme(r, F.array_min, "gx").alias("x0"), _extreme(r, F.array_min, "gy").alias("y0"), _extreme(r, F.array_max, "gx").alias("x1"), _extreme(r, F.array_max, "gy").alias("y1"))
    n = F.size(F.flatten(r)).cast("long")
    return layer.df.withColumn("mbr", mbr).withColumn("n_edges", n).withColumn("bytes", n * 16 + 16)


def tile_span(meta: GridMeta, mbr: str = "mbr") -> Column:
    """Tile columns and rows that an MBR overlaps, clipped to the raster: struct<c0, c1, r0, r1>."""
    w, h = meta.tile_w * SNAP, meta.tile_h * SNAP
    m = F.col(mbr)
    last = lambda x, n: F.least(x, long(n - 1))
    return F.struct(
        F.greatest(floor_div(m["x0"], w), long(0)).alias("c0"), last(floor_div(m["x1"], w), meta.tiles_x).alias("c1"),
        F.greatest(floor_div(m["y0"], h), long(0)).alias("r0"), last(floor_div(m["y1"], h), meta.tiles_y).alias("r1"),
    )


def stats(layer: ZoneLayer) -> DataFrame:
    """One row: n_p, n_s, mean edges, mean extents in lattice units, bytes, total height."""
    return with_mbr(layer).agg(
        F.count(F.lit(1)).alias("n_p"), F.coalesce(F.sum("n_edges"), F.lit(0)).cast("long").alias("n_s"),
        F.coalesce(F.sum(F.col("mbr.x1") - F.col("mbr.x0")), F.lit(0)).cast("long").alias("sum_w"),
        F.coalesce(F.sum(F.col("mbr.y1") - F.col("mbr.y0")), F.lit(0)).cast("long").alias("sum_h"),
        F.coalesce(F.sum("bytes"), F.lit(0)).cast("long").alias("bytes"),
    )


def contains(edge_array: Column, x: Column, y: Column) -> Column:
    """Whether a pixel's centre lies inside, by the parity of crossings at or left of it."""
    cy, cx = y * SNAP + SNAP // 2, x * SNAP + SNAP // 2
    hit = lambda e: (cy >= e["ya"]) & (cy < e["yb"]) & (e["xa"] * (e["yb"] - e["ya"]) + (cy - e["ya"]) * (e["xb"] - e["xa"]) <= cx * (e["yb"] - e["ya"]))
    return F.pmod(F.size(F.filter(edge_array, hit)), F.lit(2)) == 1


def edge_arrays(layer: ZoneLayer) -> DataFrame:
    """zone_id, mbr and all its edges as one array."""
    e = edges(layer).groupBy("zone_id").agg(F.collect_list(F.struct("xa", "ya", "xb", "yb")).alias("edges"))
    return with_mbr(layer).select("zone_id", "mbr").join(e.hint("merge"), "zone_id")


# ---- other vector types


def points(meta: GridMeta, df: DataFrame, zone_id: str, lon: Column, lat: Column) -> DataFrame:
    """Each point's pixel: zone_id, x, y; an equi join with pixels selects them."""
    gx, gy = lon, lat
    x, y = floor_div(gx.cast("long"), SNAP), floor_div(gy.cast("long"), SNAP)
    return df.select(F.col(zone_id).cast("long").alias("zone_id"), x.alias("x"), y.alias("y")).where((F.col("x") >= 0) & (F.col("x") < meta.cols) & (F.col("y") >= 0) & (F.col("y") < meta.rows))


def lines(meta: GridMeta, layer: ZoneLayer) -> DataFrame:
    """Pixels that polylines cross: zone_id, x, y, one row each; rings are read as open lines."""
    seg = layer.df.select("zone_id", F.explode("rings").alias("r")).where(F.size("r") > 1)
    pairs = F.zip_with(F.slice("r", F.lit(1), F.size("r") - 1), F.slice("r", F.lit(2), F.size("r") - 1), lambda a, b: F.struct(a.alias("a"), b.alias("b")))
    seg = seg.select("zone_id", F.explode(pairs).alias("s")).select("zone_id", "s.a", "s.b")
    steps = F.greatest(F.abs(F.col("b.gx") - F.col("a.gx")), F.abs(F.col("b.gy") - F.col("a.gy")), F.lit(1))
    at = seg.withColumn("n", steps).withColumn("i", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n"))))
    along = lambda c: floor_div(floor_div(F.col(f"a.{c}") * F.col("n") + (F.col(f"b.{c}") - F.col(f"a.{c}")) * F.col("i"), F.col("n")), SNAP)
    px = at.select("zone_id", along("gx").alias("x"), along("gy").alias("y")).distinct()
    return px.where((F.col("x") >= 0) & (F.col("x") < meta.cols) & (F.col("y") >= 0) & (F.col("y") < meta.rows))


# ---- chunks and spatial partitions


@dataclass(frozen=True)
class ChunkSpec:
    """``by``: 'polygons', 'bytes' or 'none'; ``size``: polygons or bytes a chunk."""

    by: str = "polygons"
    size: int = 5000


#: Width of the key ranges that running sums are made in before they are put together.
COARSE = 1 << 20


def running_total(df: DataFrame, key: str, amount: Column, name: str) -> DataFrame:
    """Adds the sum of ``amount`` over smaller keys, without a global window.

    Sums run inside coarse key ranges; the ranges' totals, few rows, are summed up once.
    """
    coarse = floor_div(F.col(key), COARSE)
    with_range = df.withColumn("__range", coarse).withColumn("__amount", amount)
    per = with_range.groupBy("__range").agg(F.sum("__amount").alias("__total"))
    before = Window.orderBy("__range").rowsBetween(Window.unboundedPreceding, -1)
    per = per.select(F.col("__range").alias("__r"), F.coalesce(F.sum("__total").over(before), F.lit(0)).alias("__base"))
    inside = Window.partitionBy("__range").orderBy(key).rowsBetween(Window.unboundedPreceding, -1)
    local = with_range.withColumn(name, F.coalesce(F.sum("__amount").over(inside), F.lit(0)))
    return local.join(per, F.col("__range") == F.col("__r")).withColumn(name, (F.col(name) + F.col("__base")).cast("long")).drop("__range", "__amount", "__r", "__base")


def chunk(df: DataFrame, spec: ChunkSpec = ChunkSpec()) -> DataFrame:
    """Adds chunk_id in order of zone_id. ``df`` comes from ``with_mbr``."""
    if spec.by == "none":
        return df.withColumn("chunk_id", F.lit(0))
    amount = F.lit(1).cast("long") if spec.by == "polygons" else F.col("bytes")
    before = running_total(df, "zone_id", amount, "__before")
    return before.withColumn("chunk_id", floor_div(F.col("__before"), spec.size).cast("int")).drop("__before")


def partition_spatial(df: DataFrame, kind: str = "strtile", size: int = 5000) -> DataFrame:
    """Adds chunk_id so that zones of a chunk lie near each other.

    'strtile': strips of equal numbers in x, cells of equal numbers in y inside each strip;
    'zorder' and 'hilbert': ranges of a space-filling curve; 'none': order of keys. Bounds come
    from the sample of Spark's own range partitioning; they steer balance, any are correct, and
    neither the plan nor the driver holds them.
    """
    if kind == "none":
        return chunk(df, ChunkSpec("polygons", size))
    cx, cy = floor_div(F.col("mbr.x0") + F.col("mbr.x1"), 2), floor_div(F.col("mbr.y0") + F.col("mbr.y1"), 2)
    with_c = df.withColumn("__cx", cx).withColumn("__cy", cy)
    n_chunks = max(1, math.ceil(df.count() / size))
    place = F.spark_partition_id().cast("int")
    if kind in ("zorder", "hilbert"):
        low = with_c.agg(F.min("__cx"), F.min("__cy")).first()
        zx, zy = F.greatest(F.col("__cx") - (low[0] or 0), F.lit(0)), F.greatest(F.col("__cy") - (low[1] or 0), F.lit(0))
        code = morton(zx, zy) if kind == "zorder" else hilbert(zx, zy, 22)
        return with_c.withColumn("__code", code).repartitionByRange(n_chunks, "__code").withColumn("chunk_id", place).drop("__cx", "__cy", "__code")
    if kind != "strtile":
        raise ValueError(f"unknown partitioner {kind!r}")
    strips = with_c.repartitionByRange(max(1, math.ceil(math.sqrt(n_chunks))), "__cx").withColumn("__strip", place)
    return strips.repartitionByRange(n_chunks, "__strip", "__cy").withColumn("chunk_id", place).drop("__cx", "__cy", "__strip")
