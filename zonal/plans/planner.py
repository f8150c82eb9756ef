"""The front door: choose a method from the cost model, explain the choice, run it.

The choices of joins and strategies are made here, before the optimizer sees the plan; it
keeps its freedom below them.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import accumulate, cost
from ..functions.accumulate import DEFAULT
from ..functions.cost import Params
from ..functions.grid import RasterLayer
from ..operators import baselines, selection
from ..operators import merge_ordered as mo
from ..operators import runs as R
from ..operators.selection import strategy_for
from ..operators.zones import ChunkSpec, ZoneLayer

METHODS = ("merge_ordered", "clip", "clip_tiles", "pixel_probe", "scanline", "scanline_blackbox")
#: Cost units (pixels or crossings) that starting a distributed job is worth.
STARTUP = 5e7


@dataclass(frozen=True)
class MethodPlan:
    method: str
    strategy: str
    chunk: ChunkSpec
    partitioner: str
    aggs: tuple[str, ...]
    costs: dict[str, float] = field(default_factory=dict)
    tree: str = ""

    def __str__(self) -> str:
        rows = "\n".join(f"  {k}: {v:.6g}" for k, v in self.costs.items())
        return f"method {self.method}, strategy {self.strategy}, chunks {self.chunk.by} {self.chunk.size}, partitioner {self.partitioner}\nestimates:\n{rows}\n{self.tree}"


def estimates(q: Params) -> dict[str, float]:
    return {
        "merge_ordered": cost.merge_time(q), "clip": cost.clip_time(q), "pixel_probe": cost.probe_time(q), "scanline": cost.scanline_time(q),
        "merge_disk": cost.merge_disk(q), "clip_disk": cost.clip_disk(q), "probe_disk": cost.probe_disk(q), "crossings": cost.merge_crossings(q)[1],
    }


def choose(q: Params, cores: int) -> str:
    """Scanline for small inputs, where starting up costs more than one machine's pass."""
    e = estimates(q)
    return "scanline" if e["scanline"] < STARTUP / 10 and e["scanline"] < e["merge_ordered"] / max(cores, 1) + STARTUP else "merge_ordered"


def partitioner_for(q: Params) -> str:
    """Spatial partitions pay once there are many chunks; with few they change nothing."""
    return "strtile" if q.chunks >= 8 else "none"


def plan(raster: RasterLayer, layer: ZoneLayer, aggs: tuple[str, ...] = DEFAULT, method: str = "auto", chunk: ChunkSpec = ChunkSpec(), partitioner: str = "auto", strategy: str = "auto") -> MethodPlan:
    q = Params.from_data(raster.meta, layer, chunk.size if chunk.by == "polygons" else 5000)
    if method == "auto":
        method = choose(q, layer.df.sparkSession.sparkContext.defaultParallelism)
        if method == "scanline" and (set(aggs) - set(DEFAULT) or raster.form != "pixels" or strategy == "splits" or accumulate.sum_type(raster.df.schema["v"].dataType) not in ("bigint", "double")):
            method = "merge_ordered"
    if method not in METHODS:
        raise ValueError(f"unknown method {method!r}; one of {METHODS}")
    return MethodPlan(method, strategy_for(q) if strategy == "auto" else strategy, chunk, partitioner_for(q) if partitioner == "auto" else partitioner, aggs, estimates(q))


def zonal_stats(
    raster: RasterLayer, zones: ZoneLayer, aggs: tuple[str, ...] = DEFAULT, *, method: str = "auto", chunk: ChunkSpec = ChunkSpec(),
    partitioner: str = "auto", store: str | None = None, codec: str = "snappy", strategy: str = "auto", reduce: str = "hof", keep_empty: bool = True, wide: bool = False,
    tiles_per_split: int = 64, one_file: bool = True,
) -> DataFrame:
    """One row per zone with the aggregates of the pixels whose centres it contains.

    ``strategy`` 'splits' writes the crossing store to ``store``, plans splits of
    ``tiles_per_split`` tiles from its footer, each within one file of the raster if
    ``one_file``, and reads tiles and runs side by side; the raster comes from ``read_tiles``.
    """
    p = plan(raster, zones, tuple(aggs), method, chunk, partitioner, strategy)
    if p.method == "merge_ordered":
        return mo.zonal(raster, zones, p.aggs, p.chunk, p.partitioner, store, codec, p.strategy, reduce, keep_empty, wide, tiles_per_split, one_file)
    if p.method == "clip":
        return baselines.clip(raster, zones, p.aggs, empty=keep_empty)
    if p.method == "clip_tiles":
        return baselines.clip_by_tiles(raster, zones, p.aggs, empty=keep_empty)
    if p.method == "pixel_probe":
        return baselines.pixel_probe(raster, zones, p.aggs, empty=keep_empty)
    if set(p.aggs) != set(DEFAULT):
        raise ValueError("the scanline baselines compute min, max, sum and count")
    run = baselines.scanline if p.method == "scanline" else baselines.scanline_blackbox
    return run(raster, zones, empty=keep_empty).select("zone_id", "min_v", "max_v", "sum_v", "cnt")


def explain_zonal(raster: RasterLayer, zones: ZoneLayer, **how) -> MethodPlan:
    """The plan that ``zonal_stats`` would run, with estimates and Spark's physical plan."""
    keys = ("aggs", "method", "chunk", "partitioner", "strategy")
    p = plan(raster, zones, **{k: v for k, v in how.items() if k in keys})
    tree = zonal_stats(raster, zones, **how)._jdf.queryExecution().explainString(zones.df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
    return MethodPlan(p.method, p.strategy, p.chunk, p.partitioner, p.aggs, p.costs, tree)


def zone_pairs(raster: RasterLayer, zones: ZoneLayer, strategy: str = "auto") -> DataFrame:
    """(zone_id, v) pairs, for accumulators of all kinds."""
    runs = mo.intersect(zones, raster.meta, ChunkSpec("none")).select("zone_id", "tile_id", "y", "x0", "x1")
    return mo.selected(raster, runs, selection.resolved(strategy, zones, raster.meta))


def zonal_histogram(raster: RasterLayer, zones: ZoneLayer, bins: tuple[float, float, int] | None = None, as_map: bool = False) -> DataFrame:
    return accumulate.histogram(zone_pairs(raster, zones), bins, as_map)


def zonal_custom(raster: RasterLayer, zones: ZoneLayer, accumulator: accumulate.Accumulator) -> DataFrame:
    return accumulate.accumulate_custom(zone_pairs(raster, zones), accumulator)


def areal_interpolate(source: ZoneLayer, target: ZoneLayer, raster: RasterLayer, counts: DataFrame, class_weights: dict[int, int]) -> DataFrame:
    """Counts of source zones spread to pixels by class weight and gathered by target zones.

    estimate(t) = sum over s of count(s) * weighted pixels of s in t / weighted pixels of s.
    ``counts``: zone_id, population of source zones. Whole numbers up to the last division.
    """
    w = F.lit(0).cast("long")
    for c, weight in class_weights.items():
        w = F.when(F.col("v") == c, F.lit(weight).cast("long")).otherwise(w)
    meta = raster.meta
    weighted = RasterLayer(raster.df.select("x", "y", w.alias("v")), meta)
    src = R.cut(R.zone_runs(source, meta), meta)
    in_source = selection.range_join(weighted, src, selection.resolved("auto", source, meta)).withColumnRenamed("zone_id", "source_id")
    whole = in_source.groupBy("source_id").agg(F.sum("v").alias("whole"))
    tgt = R.cut(R.zone_runs(target, meta), meta)
    both = selection.range_join(RasterLayer(in_source, meta), tgt, selection.resolved("auto", target, meta))
    part = both.groupBy("source_id", "zone_id").agg(F.sum("v").alias("part"))
    shares = part.join(whole, "source_id").join(counts.select(F.col("zone_id").alias("source_id"), "population"), "source_id").where("whole > 0")
    out = shares.groupBy("zone_id").agg(F.sum(F.col("population") * F.col("part") / F.col("whole")).alias("estimate"))
    return target.df.select("zone_id").join(out, "zone_id", "left").withColumn("estimate", F.coalesce("estimate", F.lit(0.0)))
