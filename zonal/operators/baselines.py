"""The methods that the merge-ordered one is compared with.

clip: one mask a polygon, joined by pixel position. pixel-probe: an index on the polygons,
looked up for every pixel. scanline: one machine, one pass over rows. black-box parallel
scanline: the scanline run whole for every part of the vector layer.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.accumulate import DEFAULT, is_whole, keep_empty, merge_partials, sum_type, value_aggs
from ..functions.arith import floor_div, long
from ..functions.grid import SNAP, GridMeta, RasterLayer, explode_tiles, tile_id, tile_pixels, tile_place
from . import runs as R
from . import selection, zones
from .merge_ordered import cut_runs, selected
from .zones import ZoneLayer


def as_pixels(raster: RasterLayer) -> DataFrame:
    return raster.df if raster.form == "pixels" else explode_tiles(raster)


def as_tiles(raster: RasterLayer) -> RasterLayer:
    return raster if raster.form == "tiles" else tile_pixels(raster)


def spread(df: DataFrame) -> int:
    """Partitions for rows that grow later on: what is small now must not be put together."""
    return int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


# ---- clip


def mask(layer: ZoneLayer, meta: GridMeta, dense: bool = False, keep: tuple[str, ...] = ()) -> DataFrame:
    """keep.., zone_id, x, y, m: a zone's mask at the raster's resolution; ``dense`` keeps its zeros."""
    inside = R.zone_runs(layer, meta, keep)
    px = inside.select(*keep, "zone_id", "y", F.explode(F.sequence("x0", F.col("x1") - 1)).alias("x"))
    if not dense:
        return px.select(*keep, "zone_id", "x", "y", F.lit(1).alias("m"))
    if keep:
        raise ValueError("a dense mask keeps no other columns")
    m = zones.with_mbr(layer).select("zone_id", "mbr")
    x0, x1 = F.greatest(floor_div(F.col("mbr.x0"), SNAP), long(0)), F.least(floor_div(F.col("mbr.x1"), SNAP), long(meta.cols - 1))
    y0, y1 = F.greatest(floor_div(F.col("mbr.y0"), SNAP), long(0)), F.least(floor_div(F.col("mbr.y1"), SNAP), long(meta.rows - 1))
    box = m.select("zone_id", x0.alias("x0"), x1.alias("x1"), y0.alias("y0"), y1.alias("y1")).where("x0 <= x1 and y0 <= y1")
    rows = box.select("zone_id", "x0", "x1", F.explode(F.sequence("y0", "y1")).alias("y"))
    cells = rows.repartition(spread(rows), "zone_id", "y").select("zone_id", F.explode(F.sequence("x0", "x1")).alias("x"), "y")
    # Spark takes exploded rows for as few as the zones, and would broadcast the mask
    return cells.join(px.withColumn("m", F.lit(1)).hint("merge"), ["zone_id", "x", "y"], "left").select("zone_id", "x", "y", F.coalesce("m", F.lit(0)).alias("m"))


def clip(raster: RasterLayer, layer: ZoneLayer, aggs: tuple[str, ...] = DEFAULT, dense: bool = False, empty: bool = True) -> DataFrame:
    """Mask and raster meet in a hash join on pixel position."""
    m = mask(layer, raster.meta, dense).hint("shuffle_hash")
    met = as_pixels(raster).join(m, ["x", "y"]).where("m = 1")
    out = met.groupBy("zone_id").agg(*value_aggs(aggs, met))
    return keep_empty(out, layer.df) if empty else out


def overlapped_tiles(layer: ZoneLayer, meta: GridMeta) -> DataFrame:
    """zone_id, tile_id of all tiles that a zone's bounding box overlaps: what clip reads."""
    span = zones.with_mbr(layer).select("zone_id", zones.tile_span(meta).alias("s")).where("s.c0 <= s.c1 and s.r0 <= s.r1")
    cols = span.select("zone_id", "s", F.explode(F.sequence("s.c0", "s.c1")).alias("c"))
    cells = cols.select("zone_id", "c", F.explode(F.sequence("s.r0", "s.r1")).alias("r"))
    x, y = F.col("c") * meta.tile_w, F.col("r") * meta.tile_h
    return cells.select("zone_id", tile_id(meta, x, y).alias("tile_id"))


def clip_by_tiles(raster: RasterLayer, layer: ZoneLayer, aggs: tuple[str, ...] = DEFAULT, per_zone_jobs: bool = False, max_jobs: int = 100, empty: bool = True) -> DataFrame:
    """Every zone reads all whole tiles it overlaps: a tile under k zones is read k times.

    ``per_zone_jobs`` runs one query a zone, as a raster database is driven; for small layers.
    """
    tiled = as_tiles(raster)
    if per_zone_jobs:
        ids = [r[0] for r in layer.df.select("zone_id").orderBy("zone_id").limit(max_jobs + 1).collect()]
        if len(ids) > max_jobs:
            raise ValueError(f"more than {max_jobs} zones: one job a zone is for small layers")
        parts = [clip_by_tiles(tiled, ZoneLayer(layer.df.where(F.col("zone_id") == i)), aggs, empty=empty) for i in ids]
        return reduce(DataFrame.unionByName, parts)
    meta = raster.meta
    w, h = meta.tile_w, meta.tile_h
    inside = R.cut(R.zone_runs(layer, meta), meta).groupBy("zone_id", "tile_id").agg(F.collect_list(F.struct("y", "x0", "x1")).alias("runs"))
    need = overlapped_tiles(layer, meta).join(inside.hint("merge"), ["zone_id", "tile_id"], "left")  # a tile may be read for nothing
    r, c = tile_place(meta, F.col("tile_id"))
    row = lambda u: (u["y"] - F.col("__y")) * w + u["x0"] - F.col("__x") + 1
    met = tiled.df.join(need.hint("merge"), "tile_id").withColumn("__y", r * h).withColumn("__x", c * w)
    vs = F.flatten(F.transform("runs", lambda u: F.slice(F.col("values"), row(u).cast("int"), (u["x1"] - u["x0"]).cast("int"))))
    got = met.select("zone_id", F.explode(vs).alias("v")).where("v is not null")
    out = got.groupBy("zone_id").agg(*value_aggs(aggs, got))
    return keep_empty(out, layer.df) if empty else out


# ---- pixel-probe

#: An index with up to this many edges, copies counted, may be a broadcast table.
BROADCAST_EDGES = 2_000_000


#: Zones a leaf of the k-d index is made for, levels of its tree, and sampled centres a leaf.
LEAF_ZONES, MAX_DEPTH, LEAF_SAMPLE = 64, 14, 8


class KdTree:
    """A full binary tree of splits in heap order: node i has the children 2i and 2i + 1.

    Splits are medians of a sample of zone centres, at most ``LEAF_SAMPLE << MAX_DEPTH``; they
    steer balance, any are correct. Pixels and boxes go down it inside the plan, so neither
    meets a list of leaves.
    """

    def __init__(self, centres: list[tuple[int, int]], depth: int):
        self.depth = depth
        far = 1 << 40
        at, axis, held = [far] * (1 << depth), [0] * (1 << depth), {1: centres}
        for node in range(1, 1 << depth):
            pts = held.pop(node, [])
            if not pts:
                continue  # an empty node: all goes to its lower child
            a = axis[node] = 0 if len({p[0] for p in pts}) >= len({p[1] for p in pts}) else 1
            pts.sort(key=lambda p: p[a])
            at[node] = pts[len(pts) // 2][a]
            held[2 * node], held[2 * node + 1] = [p for p in pts if p[a] < at[node]], [p for p in pts if p[a] >= at[node]]
        folded = lambda xs: F.split(F.lit(",".join(map(str, xs))), ",").cast("array<bigint>")
        self._at, self._axis = folded(at), folded(axis)
        self._levels = F.sequence(F.lit(1), F.lit(depth))

    def _split(self, node: Column, x: Column, y: Column) -> tuple[Column, Column]:
        """A node's split and the coordinate it compares."""
        return F.get(self._at, node), F.when(F.get(self._axis, node) == 0, x).otherwise(y)

    def leaf(self, x: Column, y: Column) -> Column:
        def down(node: Column, _: Column) -> Column:
            at, c = self._split(node, x, y)
            return (node * 2 + F.when(c >= at, 1).otherwise(0)).cast("int")

        return F.aggregate(self._levels, F.lit(1), down)

    def leaves(self, box: Column) -> Column:
        """All leaves that a box meets."""

        def children(node: Column) -> Column:
            at, low = self._split(node, box["x0"], box["y0"])
            _, high = self._split(node, box["x1"], box["y1"])
            return F.when(high < at, F.array(node * 2)).when(low >= at, F.array(node * 2 + 1)).otherwise(F.array(node * 2, node * 2 + 1))

        return F.aggregate(self._levels, F.array(F.lit(1)), lambda nodes, _: F.flatten(F.transform(nodes, children)))


def probe_index(layer: ZoneLayer, meta: GridMeta, kind: str = "grid", leaves: int = 64) -> tuple[DataFrame, KdTree | None]:
    """(index, tree). 'grid': cell -> zones by bounding box; 'kd': leaves of a k-d split of a
    sample of zone centres, ``leaves`` at least and more as the layer grows; 'none': one list."""
    z = zones.edge_arrays(layer)
    if kind == "none":
        return z, None
    if kind == "grid":
        span = z.withColumn("s", zones.tile_span(meta)).where("s.c0 <= s.c1 and s.r0 <= s.r1")
        cells = span.withColumn("c", F.explode(F.sequence("s.c0", "s.c1"))).withColumn("r", F.explode(F.sequence("s.r0", "s.r1")))
        return cells.select((F.col("r") * meta.tiles_x + F.col("c")).alias("cell"), "zone_id", "mbr", "edges"), None
    if kind != "kd":
        raise ValueError(f"unknown index {kind!r}")
    boxes = zones.with_mbr(layer)
    n = boxes.count()
    depth = min(MAX_DEPTH, (max(leaves, n // LEAF_ZONES, 2) - 1).bit_length())
    some = boxes.where(F.pmod(F.xxhash64("zone_id"), long(max(n, 1))) < (LEAF_SAMPLE << depth))
    middle = lambda c: floor_div(F.col(f"mbr.{c}0") + F.col(f"mbr.{c}1"), 2)
    tree = KdTree([(r.x, r.y) for r in some.select(middle("x").alias("x"), middle("y").alias("y")).orderBy("x", "y").collect()], depth)
    # many zones may share a centre, so a leaf is also cut at tiles: a box goes down tile by tile
    span = z.withColumn("s", zones.tile_span(meta)).where("s.c0 <= s.c1 and s.r0 <= s.r1")
    cells = span.withColumn("c", F.explode(F.sequence("s.c0", "s.c1"))).withColumn("r", F.explode(F.sequence("s.r0", "s.r1")))
    w, h = meta.tile_w * SNAP, meta.tile_h * SNAP
    part = F.struct(
        F.greatest("mbr.x0", F.col("c") * w).alias("x0"), F.greatest("mbr.y0", F.col("r") * h).alias("y0"),
        F.least("mbr.x1", (F.col("c") + 1) * w - 1).alias("x1"), F.least("mbr.y1", (F.col("r") + 1) * h - 1).alias("y1"),
    )
    pieces = cells.select((F.col("r") * meta.tiles_x + F.col("c")).alias("tile"), "zone_id", "mbr", "edges", part.alias("part"))
    return pieces.select(F.explode(tree.leaves(F.col("part"))).alias("cell"), "tile", "zone_id", "mbr", "edges"), tree


def probe_lookup(raster: RasterLayer, index: DataFrame, tree: KdTree | None, kind: str, broadcast: bool = True) -> DataFrame:
    """(zone_id, v): every pixel finds its zones by cell, bounding box and exact parity."""
    px = as_pixels(raster).select("x", "y", "v")
    cx, cy = F.col("x") * SNAP + SNAP // 2, F.col("y") * SNAP + SNAP // 2
    box = (F.col("mbr.x0") <= cx) & (F.col("mbr.x1") >= cx) & (F.col("mbr.y0") <= cy) & (F.col("mbr.y1") >= cy)
    idx = F.broadcast(index) if broadcast else index.hint("merge")
    m = raster.meta
    tile = floor_div(F.col("y"), m.tile_h) * m.tiles_x + floor_div(F.col("x"), m.tile_w)
    if kind == "none":
        met = px.join(idx, box)
    elif kind == "grid":
        met = px.withColumn("cell", tile).join(idx, "cell").where(box)
    else:
        leaf = F.coalesce(tree.leaf(cx, cy), F.lit(0))  # never null: else Spark goes down twice, once to filter
        met = px.withColumn("cell", leaf).withColumn("tile", tile).join(idx, ["cell", "tile"]).where(box)
    return met.where(zones.contains(F.col("edges"), F.col("x"), F.col("y"))).select("zone_id", "v")


def pixel_probe(raster: RasterLayer, layer: ZoneLayer, aggs: tuple[str, ...] = DEFAULT, index: str = "grid", materialize_to: str | None = None, empty: bool = True) -> DataFrame:
    """``materialize_to`` writes the index as Parquet and reads it again: the disk variant.
    An index above ``BROADCAST_EDGES`` edges isn't broadcast; one list can't do without."""
    meta = raster.meta
    built, tree = probe_index(layer, meta, index)
    boxes = zones.with_mbr(layer).withColumn("s", zones.tile_span(meta))
    cells = F.greatest(F.col("s.c1") - F.col("s.c0") + 1, long(0)) * F.greatest(F.col("s.r1") - F.col("s.r0") + 1, long(0)) if index != "none" else long(1)
    small = (boxes.agg(F.sum(F.col("n_edges") * cells)).first()[0] or 0) <= BROADCAST_EDGES
    if index == "none" and not small:
        raise ValueError(f"without an index every pixel meets every zone: for layers up to {BROADCAST_EDGES} edges")
    if materialize_to:
        built.write.parquet(materialize_to)
        built = built.sparkSession.read.parquet(materialize_to)
    met = probe_lookup(raster, built, tree, index, small)
    out = met.groupBy("zone_id").agg(*value_aggs(aggs, met))
    return keep_empty(out, layer.df) if empty else out


# ---- scanline


def row_range(layer: ZoneLayer, meta: GridMeta) -> tuple[int, int]:
    """Raster rows that the layer's bounding box spans: [first, behind last)."""
    r = zones.with_mbr(layer).agg(F.min("mbr.y0"), F.max("mbr.y1")).first()
    if r[0] is None:
        return 0, 0
    return max(0, r[0] // SNAP), min(meta.rows, r[1] // SNAP + 1)


def scanline(raster: RasterLayer, layer: ZoneLayer, empty: bool = True) -> DataFrame:
    """One task on purpose: rows in order, all zones of a row before the next row."""
    meta, px = raster.meta, as_pixels(raster)
    kind = px.schema["v"].dataType
    total_type = sum_type(kind)
    if total_type not in ("bigint", "double"):
        raise ValueError("the scanline adds up whole numbers and doubles, not decimals")
    number = int if is_whole(kind) else float
    lo, hi = row_range(layer, meta)
    runs = R.zone_runs(layer, meta).groupBy("y").agg(F.sort_array(F.collect_list(F.struct("zone_id", "x0", "x1"))).alias("runs"))
    rows = px.where((F.col("y") >= lo) & (F.col("y") < hi) & F.col("v").isNotNull()).select("x", "y", F.col("v").cast(total_type).alias("v"))
    rows = rows.groupBy("y").agg(F.sort_array(F.collect_list(F.struct("x", "v"))).alias("px"))
    lines = rows.join(runs, "y").coalesce(1).sortWithinPartitions("y").select("px.x", "px.v", "runs.zone_id", "runs.x0", "runs.x1")

    def sweep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        total: dict[int, list] = {}
        for b in batches:
            for i in range(b.num_rows):
                x, v, zone, x0, x1 = (c[i].values.to_numpy(zero_copy_only=False) for c in b.columns)
                first, last = np.searchsorted(x, x0), np.searchsorted(x, x1)
                for z, s, e in zip(zone.tolist(), first.tolist(), last.tolist(), strict=True):
                    if e > s:
                        part = v[s:e]
                        low, high = number(part.min()), number(part.max())
                        t = total.setdefault(z, [0, number(0), low, high])
                        t[0] += e - s
                        t[1] += number(part.sum())
                        t[2], t[3] = min(t[2], low), max(t[3], high)
        values = pa.int64() if number is int else pa.float64()
        kinds = [pa.int64(), pa.int64(), values, values, values]
        cols = [list(total), *([t[i] for t in total.values()] for i in range(4))]
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["zone_id", "cnt", "sum_v", "min_v", "max_v"])

    out = lines.mapInArrow(sweep, f"zone_id bigint, cnt bigint, sum_v {total_type}, min_v {total_type}, max_v {total_type}")
    return keep_empty(out, layer.df) if empty else out


def scanline_blackbox(raster: RasterLayer, layer: ZoneLayer, n_splits: int = 4, empty: bool = True) -> DataFrame:
    """The whole raster is read once for every vector split, each with its own scanline."""
    parts = [scanline(raster, ZoneLayer(layer.df.where(F.pmod("zone_id", long(n_splits)) == i)), empty=False) for i in range(n_splits)]
    out = merge_partials(reduce(DataFrame.unionByName, parts), ["zone_id"], ("count", "sum", "min", "max"))
    return keep_empty(out, layer.df) if empty else out


# ---- parts


def run_in_parts(raster: RasterLayer, layer: ZoneLayer, max_bytes: int, method: Callable[[RasterLayer, DataFrame], DataFrame]) -> DataFrame:
    """Split the vector layer by size, run ``method`` on each part, add the results up.

    Parts are rows of one plan, told apart by ``chunk_id``: a part's zones lie in one task,
    and neither plan nor driver grows with the number of parts. ``method`` gives partials.
    """
    sized = zones.chunk(zones.with_mbr(layer), zones.ChunkSpec("bytes", max_bytes)).select("chunk_id", "zone_id", "rings")
    parts = sized.repartition(spread(sized), "chunk_id")
    return keep_empty(merge_partials(method(raster, parts), ["zone_id"], DEFAULT), layer.df)


def merge_parts(raster: RasterLayer, parts: DataFrame) -> DataFrame:
    """Partials of a part and zone by the merge-ordered method."""
    runs = cut_runs(R.zone_runs(parts, raster.meta, ("chunk_id",)), raster.meta)
    got = selected(raster, runs, selection.resolved("auto", ZoneLayer(parts), raster.meta))
    by = [c for c in ("chunk_id", "zone_id") if c in got.columns]
    return got.groupBy(*by).agg(*value_aggs(DEFAULT, got))


def clip_parts(raster: RasterLayer, parts: DataFrame) -> DataFrame:
    """Partials of a part and zone by clip."""
    met = as_pixels(raster).join(mask(parts, raster.meta, keep=("chunk_id",)).hint("shuffle_hash"), ["x", "y"])
    return met.groupBy("chunk_id", "zone_id").agg(*value_aggs(DEFAULT, met))


def fused(raster: RasterLayer, layer: ZoneLayer, mode: str, strategy: str = "auto") -> DataFrame:
    """Partials a run, merged: for comparing the fused reductions with pairs."""
    tiled = as_tiles(raster)
    runs = R.cut(R.zone_runs(layer, raster.meta), raster.meta)
    met = selection.reduce_runs(tiled, runs, mode, selection.resolved(strategy, layer, raster.meta))
    return keep_empty(merge_partials(met, ["zone_id"], DEFAULT), layer.df)
