"""Selection: runs meet tiles (or pixels), and the values under a run are reduced or listed.

The (zone, value) pairs and run partials flow into the partial aggregate of the same task;
no exchange lies between, and nothing is stored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import cost
from ..functions.accumulate import is_whole, sum_type
from ..functions.cost import Params
from ..functions.grid import GridMeta, RasterLayer, tile_id, tile_place
from .zones import ZoneLayer

#: Runs up to this many rows may be broadcast; the cost model bounds them first.
BROADCAST_RUNS = 2_000_000
STRATEGIES = ("broadcast_runs", "colocated", "hash", "splits")


def strategy_for(q: Params) -> str:
    """Broadcast runs only if the model bounds them: crossings and tile pieces they are cut to."""
    pieces = cost.merge_crossings(q)[1] / 2 * (1 + q.w_p / (q.w_t * q.p))
    return "broadcast_runs" if pieces <= BROADCAST_RUNS / 4 else "colocated"


def resolved(strategy: str, layer: ZoneLayer, meta: GridMeta) -> str:
    """'auto' becomes what the layer's statistics allow: nothing is broadcast unmeasured."""
    if strategy == "auto":
        return strategy_for(Params.from_data(meta, layer))
    if strategy not in STRATEGIES:
        raise ValueError(f"unknown strategy {strategy!r}; auto or one of {STRATEGIES}")
    return strategy


def _sent(runs: DataFrame, strategy: str) -> DataFrame:
    if strategy == "broadcast_runs":
        return F.broadcast(runs)
    return runs.hint({"colocated": "merge", "hash": "shuffle_hash", "splits": "merge"}[strategy])


def range_join(layer: RasterLayer, runs: DataFrame, strategy: str = "broadcast_runs") -> DataFrame:
    """(zone columns, v) pairs of a pixel raster: equal (tile, row), and x inside the run.

    Loose pixels have no storage order, so only broadcast runs leave them where they are.
    """
    meta = layer.meta
    p = layer.df.withColumn("tile_id", tile_id(meta, F.col("x"), F.col("y"))).withColumnRenamed("y", "__y").withColumnRenamed("tile_id", "__tile")
    r = _sent(runs, strategy)
    on = (F.col("__tile") == r["tile_id"]) & (F.col("__y") == r["y"]) & (F.col("x") >= r["x0"]) & (F.col("x") < r["x1"])
    extra = [c for c in layer.df.columns if c not in ("x", "y", "v")]
    return p.join(r, on).select(*[r[c] for c in runs.columns if c not in ("tile_id", "y", "x0", "x1", *extra)], *extra, "x", F.col("__y").alias("y"), "v")


def work_units(runs: DataFrame) -> DataFrame:
    """chunk_id, tile_id, runs: all runs of a chunk in a tile, in the order its cells are stored."""
    if "chunk_id" not in runs.columns:
        runs = runs.withColumn("chunk_id", F.lit(0))
    listed = F.sort_array(F.collect_list(F.struct("y", "zone_id", "x0", "x1")))
    return runs.groupBy("chunk_id", "tile_id").agg(listed.alias("runs"))


#: Directories that a filter on the tile table may list.
LISTED_GROUPS = 10_000


def pruned(layer: RasterLayer, units: DataFrame) -> RasterLayer:
    """Only directories of a tile table that hold a touched tile are read: the footer tells them."""
    if "tile_group" not in layer.df.columns or not layer.tiles_per_group:
        return layer
    group = F.floor(F.col("tile_id") / layer.tiles_per_group).cast("long")
    found = [r[0] for r in units.select(group.alias("g")).distinct().limit(LISTED_GROUPS + 1).collect()]
    if len(found) > LISTED_GROUPS:  # a range then says what a list can't
        lo, hi = units.agg(F.min(group), F.max(group)).first()
        return RasterLayer(layer.df.where(F.col("tile_group").between(lo, hi)), layer.meta, layer.form, layer.path, layer.tiles_per_group)
    return RasterLayer(layer.df.where(F.col("tile_group").isin(sorted(found))), layer.meta, layer.form, layer.path, layer.tiles_per_group)


def meet(layer: RasterLayer, runs: DataFrame, strategy: str = "broadcast_runs") -> DataFrame:
    """file_id, runs (zone_id, at, n), values: every tile once beside each unit that touches it.

    The join is on the tile alone: with broadcast units, a table bucketed by tile or one whose
    directories are pruned, no tile moves. Cells are addressed inside the tile, so a tile is
    neither cut into rows nor copied for its runs.
    """
    units = work_units(runs)
    tiles = pruned(layer, units).df.select("file_id", "tile_id", "values")
    meta = layer.meta
    w, h = (meta.tile_w, meta.tile_h) if meta.order == "row" else (meta.tile_h, meta.tile_w)
    r, c = tile_place(meta, F.col("tile_id"))
    if meta.order != "row":
        r, c = c, r
    base = (r * h * w + c * w).cast("long")  # a run begins at y * w + x0 - base
    met = tiles.join(_sent(units, strategy), "tile_id").withColumn("__base", base).withColumn("__w", F.lit(w).cast("long"))
    placed = F.transform("runs", lambda u: F.struct(u["zone_id"].alias("zone_id"), (u["y"] * F.col("__w") + u["x0"] - F.col("__base") + 1).cast("int").alias("at"), (u["x1"] - u["x0"]).cast("int").alias("n")))
    return met.select("file_id", placed.alias("runs"), "values")


def pairs(layer: RasterLayer, runs: DataFrame, strategy: str = "broadcast_runs") -> DataFrame:
    """(zone_id, v) pairs of a tiled raster, one row a covered pixel; nodata left out."""
    met = meet(layer, runs, strategy)
    one = lambda u: F.transform(F.slice(F.col("values"), u["at"], u["n"]), lambda v: F.struct(u["zone_id"].alias("zone_id"), v.alias("v")))
    return met.select(F.explode(F.flatten(F.transform("runs", one))).alias("p")).select("p.zone_id", "p.v").where("v is not null")


def reduce_runs(layer: RasterLayer, runs: DataFrame, mode: str = "hof", strategy: str = "broadcast_runs") -> DataFrame:
    """Partials zone_id, cnt, sum_v, min_v, max_v of each run, never one row a pixel.

    'hof': array functions inside the plan; 'arrow': segment reductions on whole Arrow batches.
    """
    met = meet(layer, runs, strategy)
    kind = met.schema["values"].dataType.elementType
    total = sum_type(kind)
    if mode == "hof":

        def partial(u):
            vs = F.filter(F.slice(F.col("values"), u["at"], u["n"]), lambda v: v.isNotNull())
            added = F.aggregate(vs, F.lit(0).cast(total), lambda a, v: (a + v.cast(total)).cast(total))
            return F.struct(
                u["zone_id"].alias("zone_id"), F.size(vs).cast("long").alias("cnt"), F.when(F.size(vs) > 0, added).alias("sum_v"),
                F.array_min(vs).alias("min_v"), F.array_max(vs).alias("max_v"),
            )

        return met.select(F.explode(F.transform("runs", partial)).alias("p")).select("p.*")
    if mode != "arrow":
        raise ValueError(f"unknown reduction {mode!r}; 'hof', 'arrow' or 'pairs'")
    if total not in ("bigint", "double"):
        raise ValueError("decimals are reduced by 'hof' or 'pairs'")
    return met.select("runs", "values").mapInArrow(_segment_reduce(is_whole(kind)), f"zone_id bigint, cnt bigint, sum_v {total}, min_v {total}, max_v {total}")


def _segment_reduce(whole: bool):
    wide, least, most = (np.int64, np.iinfo(np.int64).min, np.iinfo(np.int64).max) if whole else (np.float64, -np.inf, np.inf)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            runs, lists = b.column(0), b.column(1)
            flat = lists.values
            valid = pc.is_valid(flat).to_numpy(zero_copy_only=False)
            values = pc.fill_null(flat, 0).to_numpy(zero_copy_only=False).astype(wide)
            of = np.repeat(lists.offsets.to_numpy()[:-1].astype(np.int64), np.diff(runs.offsets.to_numpy()))
            zone, at, n = (pc.struct_field(runs.flatten(), i) for i in range(3))
            lo = of + at.to_numpy(zero_copy_only=False) - 1
            between = np.stack([lo, lo + n.to_numpy(zero_copy_only=False)], axis=1).reshape(-1)
            # segments may overlap: every second of the reductions between their ends counts
            parts = lambda f, x, none: f.reduceat(np.append(x, none), between)[::2] if len(between) else np.empty(0, x.dtype)
            cnt = parts(np.add, valid.astype(np.int64), 0)
            cols = [parts(np.add, np.where(valid, values, 0), 0), parts(np.minimum, np.where(valid, values, most), most), parts(np.maximum, np.where(valid, values, least), least)]
            cols = [pa.array(c.astype(wide), mask=cnt == 0) for c in cols]
            yield pa.RecordBatch.from_arrays([zone, pa.array(cnt), *cols], ["zone_id", "cnt", "sum_v", "min_v", "max_v"])

    return run
