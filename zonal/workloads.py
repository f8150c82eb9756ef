"""The study's workloads on the given tables, as registered queries with SQL beside them."""

from __future__ import annotations

import shutil
import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracle as O
from .functions import cost, grid, measures
from .functions.arith import floor_div
from .functions.cost import Params
from .functions.grid import RasterLayer
from .operators import baselines, splits, store, zones
from .operators import merge_ordered as mo
from .operators import runs as R
from .operators.zones import ChunkSpec, ZoneLayer
from .plans import planner
from .sources import formats
from .sources.layers import layers, raster, table, zone_layer

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}

AREA_LAYERS = ("ZN", "ZR", "ZS", "ZC", "ZP", "ZB")
CHUNKS = (5, 20, 100, 500, 1500)
CLASS_WEIGHTS = {1: 5, 2: 4, 3: 3, 4: 2, 5: 1}


def register(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(query: Query) -> Query:
        QUERIES[name] = query
        if sql is not None:
            ORACLE_SQL[name] = sql
        return query

    return add


def scratch(spark: SparkSession, tag: str) -> str:
    """A new folder that executors share: below spark.checkpoint.dir; temporary where all of Spark
    is one JVM, as in tests."""
    there = spark.conf.get("spark.checkpoint.dir", None)
    if there:
        return f"{there.rstrip('/')}/{tag}-{uuid.uuid4().hex[:12]}"
    master = spark.sparkContext.master
    if master.startswith("local-cluster") or not master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
    import atexit

    path = tempfile.mkdtemp(prefix=f"zonal-{tag}-")
    atexit.register(shutil.rmtree, path, ignore_errors=True)
    return f"file://{path}/data"


def tiled(layer: RasterLayer, w: int | None = None, h: int | None = None, order: str = "row") -> RasterLayer:
    meta = layer.meta.with_tiles(w or layer.meta.tile_w, h or layer.meta.tile_h, order)
    return grid.tile_pixels(RasterLayer(layer.df, meta))


# ---- end to end: zone layers by raster layers

PAIRS = {
    "zs_nation_orders": ("ZN", "RO"), "zs_supplier_orders": ("ZS", "RO"), "zs_customer_orders": ("ZC", "RO"), "zs_part_orders": ("ZP", "RO"),
    "zs_region_orders": ("ZR", "RO"), "zs_comb_orders": ("ZB", "RO"), "zs_nation_events": ("ZN", "RE"), "zs_customer_events": ("ZC", "RE"),
    "zs_nation_lineitem": ("ZN", "RP"), "zs_supplier_embeddings": ("ZS", "RM"), "zs_nation_documents": ("ZN", "RD"), "zs_nation_labels": ("ZN", "RL"),
}
ZONES = {"nation": "ZN", "supplier": "ZS", "customer": "ZC", "part": "ZP", "region": "ZR"}
GRIDS = {"orders": "RO", "events": "RE", "lineitem": "RP", "embeddings": "RM"}
PAIRS |= {f"zs_{z}_{r}": (ZONES[z], GRIDS[r]) for z in ZONES for r in GRIDS}  # all pairs of five layers and four rasters


def _method(zone: str, rast: str, run: Callable[[RasterLayer, ZoneLayer], DataFrame]) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        r, z = layers(spark, sf_dir, zone, rast)
        return run(r, z)

    return query


def _merge(r: RasterLayer, z: ZoneLayer) -> DataFrame:
    return planner.zonal_stats(r, z, method="merge_ordered")


for _name, (_z, _r) in PAIRS.items():
    register(_name, O.zonal(_z, _r))(_method(_z, _r, _merge))

METHODS: dict[str, tuple[str, str, Callable[[RasterLayer, ZoneLayer], DataFrame]]] = {
    "clip_nation_orders": ("ZN", "RO", baselines.clip),
    "clip_dense_nation_orders": ("ZN", "RO", lambda r, z: baselines.clip(r, z, dense=True)),
    "clip_tiles_customer_orders": ("ZC", "RO", baselines.clip_by_tiles),
    "clip_jobs_region_orders": ("ZR", "RO", lambda r, z: baselines.clip_by_tiles(r, z, per_zone_jobs=True)),
    "probe_grid_customer_orders": ("ZC", "RO", baselines.pixel_probe),
    "probe_kd_customer_orders": ("ZC", "RO", lambda r, z: baselines.pixel_probe(r, z, index="kd")),
    "probe_bnl_nation_orders": ("ZN", "RO", lambda r, z: baselines.pixel_probe(r, z, index="none")),
    "probe_disk_customer_orders": ("ZC", "RO", lambda r, z: baselines.pixel_probe(r, z, materialize_to=scratch(z.df.sparkSession, "index"))),
    "scanline_nation_orders": ("ZN", "RO", baselines.scanline),
    "blackbox_customer_orders": ("ZC", "RO", baselines.scanline_blackbox),
    "auto_nation_orders": ("ZN", "RO", lambda r, z: planner.zonal_stats(r, z)),
    "fused_hof_customer_orders": ("ZC", "RO", lambda r, z: baselines.fused(r, z, "hof")),
    "fused_arrow_customer_orders": ("ZC", "RO", lambda r, z: baselines.fused(r, z, "arrow")),
    "colocated_customer_orders": ("ZC", "RO", lambda r, z: planner.zonal_stats(tiled(r), z, method="merge_ordered", strategy="colocated")),
    "pairs_customer_orders": ("ZC", "RO", lambda r, z: planner.zonal_stats(tiled(r), z, method="merge_ordered", reduce="pairs")),
    "parts_customer_orders": ("ZC", "RO", lambda r, z: baselines.run_in_parts(r, z, 80_000, baselines.merge_parts)),
    "parts_clip_customer_orders": ("ZC", "RO", lambda r, z: baselines.run_in_parts(r, z, 80_000, baselines.clip_parts)),
    "zs_nation_strip": ("ZN", "RO", lambda r, z: planner.zonal_stats(tiled(r, r.meta.cols, 1), z, method="merge_ordered")),
    "zs_nation_colmajor": ("ZN", "RO", lambda r, z: planner.zonal_stats(tiled(r, 16, 16, "col"), z, method="merge_ordered")),
    "zs_customer_colmajor_pixels": ("ZC", "RO", lambda r, z: planner.zonal_stats(RasterLayer(r.df, r.meta.with_tiles(16, 16, "col")), z, method="merge_ordered")),
    "store_roundtrip_customer": ("ZC", "RO", lambda r, z: planner.zonal_stats(tiled(r), z, method="merge_ordered", chunk=ChunkSpec("polygons", 500), store=scratch(z.df.sparkSession, "store"), codec="gzip")),
    "zs_customer_strtile": ("ZC", "RO", lambda r, z: planner.zonal_stats(r, z, method="merge_ordered", chunk=ChunkSpec("polygons", 100), partitioner="strtile")),
    "zs_customer_zorder": ("ZC", "RO", lambda r, z: planner.zonal_stats(r, z, method="merge_ordered", chunk=ChunkSpec("polygons", 100), partitioner="zorder")),
    "zs_customer_hilbert": ("ZC", "RO", lambda r, z: planner.zonal_stats(r, z, method="merge_ordered", chunk=ChunkSpec("polygons", 100), partitioner="hilbert")),
    "zs_customer_bytes": ("ZC", "RO", lambda r, z: planner.zonal_stats(r, z, method="merge_ordered", chunk=ChunkSpec("bytes", 20_000))),
}
for _name, (_z, _r, _run) in METHODS.items():
    register(_name, O.zonal(_z, _r))(_method(_z, _r, _run))



def _written(r: RasterLayer, per: int = 16) -> RasterLayer:
    """The raster's tiles as a written table, in directories of ``per`` neighbouring tiles."""
    path = scratch(r.df.sparkSession, "tiles")
    formats.write_tiles(tiled(r), path, per)
    return formats.read_tiles(r.df.sparkSession, path, r.meta, per)


def _bucketed(r: RasterLayer) -> RasterLayer:
    """The raster's tiles as a table bucketed by tile."""
    spark = r.df.sparkSession
    return formats.write_bucketed(tiled(r), f"zonal_tiles_{uuid.uuid4().hex[:12]}", path=scratch(spark, "bucketed"))


def _splits(r: RasterLayer, z: ZoneLayer, **how) -> DataFrame:
    return planner.zonal_stats(_written(r), z, method="merge_ordered", strategy="splits", store=scratch(z.df.sparkSession, "store"), chunk=ChunkSpec("polygons", 100), **how)


#: Answers through the footer, splits, pruned directories and buckets.
STORED: dict[str, tuple[str, str, Callable[[RasterLayer, ZoneLayer], DataFrame]]] = {
    "splits_answer_customer": ("ZC", "RO", lambda r, z: _splits(r, z, tiles_per_split=8)),
    "splits_answer_nation": ("ZN", "RO", lambda r, z: _splits(r, z, one_file=False)),
    "bucketed_customer_orders": ("ZC", "RO", lambda r, z: planner.zonal_stats(_bucketed(r), z, method="merge_ordered", strategy="colocated")),
    "pruned_supplier_orders": ("ZS", "RO", lambda r, z: planner.zonal_stats(_written(r), z, method="merge_ordered")),
    "arrow_customer_orders": ("ZC", "RO", lambda r, z: planner.zonal_stats(tiled(r), z, method="merge_ordered", reduce="arrow")),
}
for _name, (_z, _r, _run) in STORED.items():
    register(_name, O.zonal(_z, _r))(_method(_z, _r, _run))

#: Doubles with missing values by every method and every reduction.
REAL: dict[str, Callable[[RasterLayer, ZoneLayer], DataFrame]] = {
    "real_auto": lambda r, z: planner.zonal_stats(r, z),
    "real_pixels": _merge,
    "real_clip": baselines.clip,
    "real_clip_tiles": baselines.clip_by_tiles,
    "real_probe": baselines.pixel_probe,
    "real_scanline": baselines.scanline,
    "real_blackbox": baselines.scanline_blackbox,
    "real_parts": lambda r, z: baselines.run_in_parts(r, z, 1_000, baselines.merge_parts),
    "real_hof": lambda r, z: planner.zonal_stats(tiled(r), z, method="merge_ordered", reduce="hof"),
    "real_arrow": lambda r, z: planner.zonal_stats(tiled(r), z, method="merge_ordered", reduce="arrow"),
    "real_pairs": lambda r, z: planner.zonal_stats(tiled(r), z, method="merge_ordered", reduce="pairs"),
    "real_colmajor": lambda r, z: planner.zonal_stats(tiled(r, 16, 16, "col"), z, method="merge_ordered"),
    "real_splits": _splits,
}
for _name, _run in REAL.items():
    register(f"{_name}_supplier", O.zonal_real("ZS"))(_method("ZS", "RT", lambda r, z, f=_run: f(r, z).select("zone_id", "cnt", "sum_v", "min_v", "max_v")))


@register("real_avg_nation", O.zonal_real("ZN", avg=True))
def real_avg_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    r, z = layers(spark, sf_dir, "ZN", "RT")
    return planner.zonal_stats(tiled(r), z, ("count", "sum", "min", "max", "avg"), method="merge_ordered")


class SquareSum:
    """A user's accumulator: how many values, and the sum of their squares."""

    columns = "n bigint, squares bigint"

    def init(self) -> tuple[int, int]:
        return 0, 0

    def update_many(self, state: tuple[int, int], values) -> tuple[int, int]:
        return state[0] + len(values), state[1] + int((values.astype("int64") ** 2).sum())

    def merge(self, a: tuple[int, int], b: tuple[int, int]) -> tuple[int, int]:
        return a[0] + b[0], a[1] + b[1]

    def finish(self, state: tuple[int, int]) -> tuple[int, int]:
        return state


@register("custom_nation_orderprio", f"with {O.pairs('ZN', 'RC')} select zone_id, count(*) as n, cast(sum(v * v) as bigint) as squares from pair group by zone_id")
def custom_nation_orderprio(spark: SparkSession, sf_dir: str) -> DataFrame:
    r, z = layers(spark, sf_dir, "ZN", "RC")
    return planner.zonal_custom(r, z, SquareSum())


@register(
    "lines_nation",
    f"""with {O.base('ZN', 'RO')}, seg as (select zone_id, gx as ax, gy as ay, lead(gx) over s as zx, lead(gy) over s as zy from vertex window s as (partition by zone_id, ring order by i)),
st as (select *, greatest(abs(zx - ax), abs(zy - ay), 1) as n from seg where zx is not null),
p as (select zone_id, cast(floor(floor((ax * n + (zx - ax) * i) / cast(n as double)) / 16.0) as bigint) as x, cast(floor(floor((ay * n + (zy - ay) * i) / cast(n as double)) / 16.0) as bigint) as y from (select *, unnest(range(0, cast(n + 1 as bigint))) as i from st))
select distinct zone_id, x, y from p, m where x >= 0 and x < w and y >= 0 and y < h""",
)
def lines_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pixels along the nations' open outlines."""
    r, z = layers(spark, sf_dir, "ZN", "RO")
    return zones.lines(r.meta, z)


@register(
    "tile_bounds_orders",
    f"with {O.base('ZN', 'RO')}, t as (select unnest(range(((w + 15) // 16) * ((h + 15) // 16))) as tile_id from m) select tile_id, (tile_id % ((w + 15) // 16)) * 16 as x0, (tile_id // ((w + 15) // 16)) * 16 as y0, least((tile_id % ((w + 15) // 16) + 1) * 16, w) as x1, least((tile_id // ((w + 15) // 16) + 1) * 16, h) as y1 from t, m",
)
def tile_bounds_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    meta = raster(spark, sf_dir, "RO").meta
    tiles = spark.range(meta.tiles_x * meta.tiles_y).withColumnRenamed("id", "tile_id")
    return tiles.withColumn("b", grid.tile_bounds(meta, F.col("tile_id"))).select("tile_id", "b.*")


for _k in (1, 10, 50, 100, 500, 1000):
    register(f"zs_customer_first{_k}", O.zonal("ZC", "RO", f"zone_id < {_k}"))(
        _method("ZC", "RO", lambda r, z, k=_k: _merge(r, ZoneLayer(z.df.where(F.col("zone_id") < k))))
    )
    register(f"clip_customer_first{_k}", O.zonal("ZC", "RO", f"zone_id < {_k}"))(
        _method("ZC", "RO", lambda r, z, k=_k: baselines.clip_by_tiles(r, ZoneLayer(z.df.where(F.col("zone_id") < k))))
    )
for _c in CHUNKS:
    register(f"zs_customer_chunk{_c}", O.zonal("ZC", "RO"))(
        _method("ZC", "RO", lambda r, z, c=_c: planner.zonal_stats(r, z, method="merge_ordered", chunk=ChunkSpec("polygons", c)))
    )


@register("avg_nation_orders", O.zonal("ZN", "RO", avg=True))
def avg_nation_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    r, z = layers(spark, sf_dir, "ZN", "RO")
    return planner.zonal_stats(r, z, ("count", "sum", "min", "max", "avg"), method="merge_ordered")


@register("zs_nation_multifile", O.zonal("ZN", "RO"))
def zs_nation_multifile(spark: SparkSession, sf_dir: str) -> DataFrame:
    r, z = layers(spark, sf_dir, "ZN", "RO")
    return planner.zonal_stats(tiled(RasterLayer(r.df.withColumn("file_id", floor_div(F.col("y"), 32).cast("int")), r.meta)), z, method="merge_ordered")


@register("zs_nation_returnflag_files", O.zonal("ZN", "RP"))
def zs_nation_returnflag_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One file a return flag over the same cells: file sums add up, other aggregates of a
    cell need its total first, so cells are summed over files."""
    r, z = layers(spark, sf_dir, "ZN", "RP")
    px = table(spark, sf_dir, "lineitem").groupBy("l_returnflag", F.col("l_partkey").alias("x"), F.col("l_suppkey").alias("y")).agg(F.sum(F.col("l_quantity").cast("long")).alias("v"))
    return _merge(RasterLayer(px.groupBy("x", "y").agg(F.sum("v").cast("long").alias("v")), r.meta), z)


WINDOW_SQL = f"""with {O.base('ZP', 'RP')},
inside as (select px.* from px, m where y >= h // 4 and y < h // 2),
pair as (
  select zone_id, x, y, v from inside, edge
  where 16 * y + 8 >= ya and 16 * y + 8 < yb and xa * (yb - ya) + (16 * y + 8 - ya) * (xb - xa) <= (16 * x + 8) * (yb - ya)
  group by zone_id, x, y, v having count(*) % 2 = 1),
got as (select zone_id, {O.AGGS} from pair group by zone_id)
select zone.zone_id, coalesce(cnt, 0) as cnt, sum_v, min_v, max_v from zone left join got on got.zone_id = zone.zone_id"""


@register("zs_part_lineitem_window", WINDOW_SQL)
def zs_part_lineitem_window(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Many polygons over a window of a large raster."""
    r, z = layers(spark, sf_dir, "ZP", "RP")
    lo, hi = r.meta.rows // 4, r.meta.rows // 2
    return _merge(RasterLayer(r.df.where((F.col("y") >= lo) & (F.col("y") < hi)), r.meta), z)


HIST_SQL = f"with {O.pairs('ZN', 'RC')} select zone_id, v as class, count(*) as cnt from pair group by zone_id, v"


@register("hist_nation_orderprio", HIST_SQL)
def hist_nation_orderprio(spark: SparkSession, sf_dir: str) -> DataFrame:
    r, z = layers(spark, sf_dir, "ZN", "RC")
    return planner.zonal_histogram(r, z)


def _areal_sql() -> str:
    w = "case v " + " ".join(f"when {c} then {x}" for c, x in CLASS_WEIGHTS.items()) + " else 0 end"
    return f"""
with src as (with {O.pairs('ZN', 'RC')} select zone_id as s, x, y, {w} as wt from pair),
tgt as (with {O.pairs('ZS', 'RC')} select zone_id as t, x, y from pair),
whole as (select s, cast(sum(wt) as bigint) as whole from src group by s),
part as (select s, t, cast(sum(wt) as bigint) as part from src join tgt using (x, y) group by s, t),
pop as (select cast(c_nationkey as bigint) as s, count(*) as pop from customer group by 1),
est as (select t, sum(pop * part / cast(whole as double)) as e from part join whole using (s) join pop using (s) where whole > 0 group by t)
select s_suppkey as zone_id, round(coalesce(e, 0), 4) as estimate from supplier left join est on t = s_suppkey"""


@register("areal_interp_supplier", _areal_sql())
def areal_interp_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    r, src = layers(spark, sf_dir, "ZN", "RC")
    tgt = zone_layer(spark, sf_dir, "ZS", r.meta)
    people = table(spark, sf_dir, "customer").groupBy(F.col("c_nationkey").cast("long").alias("zone_id")).agg(F.count(F.lit(1)).alias("population"))
    return planner.areal_interpolate(src, tgt, r, people, CLASS_WEIGHTS).withColumn("estimate", F.round("estimate", 4))


# ---- ingestion

TILES_SQL = f"""with {O.base('ZN', 'RO')}
select (y // 16) * ((w + 15) // 16) + x // 16 as tile_id, count(*) as filled, cast(sum(v) as bigint) as sum_v,
       cast(sum(v * ((y % 16) * 16 + x % 16)) as bigint) as weighted from px, m group by 1"""


@register("ingest_tiles_orders", TILES_SQL)
def ingest_tiles_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tiles with a checksum over values and positions."""
    t = tiled(raster(spark, sf_dir, "RO")).df.select("tile_id", F.posexplode("values").alias("p", "v")).where("v is not null")
    return t.groupBy("tile_id").agg(F.count(F.lit(1)).alias("filled"), F.sum("v").alias("sum_v"), F.sum(F.col("v") * F.col("p")).cast("long").alias("weighted"))


@register("ingest_edges_customer", f"with {O.base('ZC', 'RO')} select zone_id, xa, ya, xb, yb from edge")
def ingest_edges_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, z = layers(spark, sf_dir, "ZC", "RO")
    return zones.edges(z)


# ---- the stages as tables


@register("crossings_nation", f"with {O.base('ZN', 'RO')}, {O.CROSSINGS} select zone_id, y, x from crossing")
def crossings_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    r, z = layers(spark, sf_dir, "ZN", "RO")
    return R.edge_crossings(zones.edges(z), r.meta)


@register("runs_nation", f"with {O.base('ZN', 'RO')}, {O.RUNS} select zone_id, y, x0, x1 from run")
def runs_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    r, z = layers(spark, sf_dir, "ZN", "RO")
    return R.zone_runs(z, r.meta)


FOOT_SQL = f"with {O.base('ZC', 'RO')}, {O.cut_runs(16, 16)}, foot as (select zone_id // 100 as chunk_id, tile_id, count(*) as n_runs, count(distinct zone_id) as n_zones from piece group by 1, 2)"


def _customer_footer(spark: SparkSession, sf_dir: str) -> tuple[RasterLayer, DataFrame]:
    r, z = layers(spark, sf_dir, "ZC", "RO")
    return r, store.footer(mo.intersect(z, r.meta, ChunkSpec("polygons", 100)))


@register(
    "footer_customer",
    FOOT_SQL + " select chunk_id, tile_id, cast(coalesce(sum(n_runs) over (partition by chunk_id order by tile_id rows between unbounded preceding and 1 preceding), 0) as bigint) as first_row, n_runs, n_zones from foot",
)
def footer_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, foot = _customer_footer(spark, sf_dir)
    return foot.select(F.col("chunk_id").cast("long"), "tile_id", "first_row", "n_runs", F.size("zone_ids").cast("long").alias("n_zones"))


SPLIT_SQL = FOOT_SQL + """,
isl as (select *, tile_id - row_number() over (partition by chunk_id order by tile_id) as g from foot),
part as (select *, (row_number() over (partition by chunk_id, g order by tile_id) - 1) // 8 as p from isl),
split as (select chunk_id, min(tile_id) as tile_lo, max(tile_id) as tile_hi, count(*) * 256 as est_pixels from part group by chunk_id, g, p)"""


@register("splits_customer", SPLIT_SQL + " select chunk_id, tile_lo, tile_hi, est_pixels from split")
def splits_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    r, foot = _customer_footer(spark, sf_dir)
    return splits.plan(foot, r.meta, 8).select(F.col("chunk_id").cast("long"), "tile_lo", "tile_hi", "est_pixels")


@register("units_customer", FOOT_SQL + " select chunk_id, tile_id from foot")
def units_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    r, foot = _customer_footer(spark, sf_dir)
    return splits.expand(splits.plan(foot, r.meta, 8), foot).select(F.col("chunk_id").cast("long"), "tile_id")


@register(
    "splits_onefile",
    FOOT_SQL + ", t as (select chunk_id, tile_id, (tile_id // ((w + 15) // 16)) // 2 as file_id from foot, m) select chunk_id, file_id, min(tile_id) as tile_lo, max(tile_id) as tile_hi, count(*) * 256 as est_pixels from t group by chunk_id, file_id, tile_id // 16",
)
def splits_onefile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Row bands of 32 rows are files; no split crosses one."""
    r, foot = _customer_footer(spark, sf_dir)
    files = spark.range(r.meta.tiles_x * r.meta.tiles_y).select(F.col("id").alias("tile_id"), floor_div(floor_div(F.col("id"), r.meta.tiles_x), 2).alias("file_id"))
    return splits.plan(foot, r.meta, 16, files, mode="blocks").select(F.col("chunk_id").cast("long"), "file_id", "tile_lo", "tile_hi", "est_pixels")


@register(
    "splits_by_chunk",
    f"with {O.base('ZC', 'RO')}, {O.cut_runs(16, 16)} " + " union all ".join(f"select {c} as chunk_size, count(*) as units from (select distinct zone_id // {c} as chunk_id, tile_id from piece)" for c in CHUNKS),
)
def splits_by_chunk(spark: SparkSession, sf_dir: str) -> DataFrame:
    r, z = layers(spark, sf_dir, "ZC", "RO")
    out = None
    for c in CHUNKS:
        one = store.footer(mo.intersect(z, r.meta, ChunkSpec("polygons", c))).agg(F.lit(c).alias("chunk_size"), F.count(F.lit(1)).alias("units"))
        out = one if out is None else out.unionByName(one)
    return out


@register("grid_roundtrip", f"with {O.base('ZN', 'RO')} select x, y, -180 + (x + 0.5) * 0.25 as lon, 90 - (y + 0.5) * 0.25 as lat, x as x_back, y as y_back from px".replace("0.5", "cast(0.5 as double)").replace("0.25", "cast(0.25 as double)"))
def grid_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = raster(spark, sf_dir, "RO")
    lon, lat = grid.grid_to_world(r.meta, F.col("x"), F.col("y"))
    p = r.df.select("x", "y", lon.alias("lon"), lat.alias("lat"))
    x, y = grid.world_to_grid(r.meta, F.col("lon"), F.col("lat"))
    return p.withColumn("x_back", x).withColumn("y_back", y)


# ---- cost model and measures

_STATS_SQL = """
s as (
  select count(*) as n_p, cast(sum(n) as bigint) as n_s, cast(sum(dx) as double) / count(*) / 16 * cast(0.25 as double) as w_p,
         cast(sum(dy) as double) / count(*) / 16 * cast(0.25 as double) as h_p
  from (select zone_id, count(*) as n, max(gx) - min(gx) as dx, max(gy) - min(gy) as dy from vertex group by zone_id))"""


def _per_layer(body: Callable[[str], str]) -> str:
    return " union all ".join(f"select * from ({body(z)})" for z in AREA_LAYERS)


def _params(spark: SparkSession, sf_dir: str, name: str = "RO") -> list[tuple[str, RasterLayer, ZoneLayer, Params]]:
    r = raster(spark, sf_dir, name)
    found = []
    for name in AREA_LAYERS:
        z = zone_layer(spark, sf_dir, name, r.meta)
        found.append((name, r, z, Params.from_data(r.meta, z)))
    return found


_MEAN = "(cast(n_s as double) / n_p)"
_CROSS = f"(n_s * (2 * h_p / {_MEAN}) / cast(0.25 as double))"
_CHUNKS = "greatest(1, cast(ceil(n_p / cast(5000 as double)) as bigint))"


#: Tile sizes of the rasters that the cost model is evaluated on.
_TILE = {"RO": ("16", "16"), "RP": "((w + 35) // 36) 1".rsplit(" ", 1)}


def _cost_merge_sql(z: str, r: str) -> str:
    tw, th = _TILE[r]
    return f"""with {O.base(z, r)}, {_STATS_SQL}, k as (select *, {_CROSS} as total, {_CROSS} / {_CHUNKS} as part, {_CHUNKS} as chunks from s)
select '{z}' as layer, n_p, n_s, cast(round(total) as bigint) as crossings,
  cast(round(chunks * (cast(ceil(w / cast({tw} as double)) * ceil(h / cast({th} as double)) * {tw} * {th} as double) + part + part * case when part > 1 then log2(part) else 0 end) / 1000) as bigint) as merge_kilo_units from k, m"""


def _cost_clip_sql(z: str, r: str) -> str:
    tw, th = _TILE[r]
    return f"""with {O.base(z, r)}, {_STATS_SQL}, k as (select *, cast(ceil(w_p / ({tw} * cast(0.25 as double))) * ceil(h_p / ({th} * cast(0.25 as double))) as bigint) as tiles from s, m)
select '{z}' as layer, tiles, cast(n_p * tiles * {tw} * {th} as bigint) as clip_pixels, cast(round(n_s * case when {_MEAN} > 1 then log2({_MEAN}) else 0 end) as bigint) as sort_units,
  cast(round((cast(n_s as double) * log2(n_s) + w * h * log2(n_s)) / 1000) as bigint) as probe_kilo_units from k"""


def _disk_sql(z: str, r: str) -> str:
    tw, th = _TILE[r]
    return f"""with {O.base(z, r)}, {_STATS_SQL}, k as (select *, {_CROSS} as total, {_CHUNKS} as chunks, n_s * 16 + n_p * 16 as bytes, ceil(w_p / ({tw} * cast(0.25 as double))) * ceil(h_p / ({th} * cast(0.25 as double))) as tiles from s, m)
select '{z}' as layer, cast(round(bytes + 2 * total * 24 + chunks * ceil(w / cast({tw} as double)) * ceil(h / cast({th} as double)) * {tw} * {th} * 8) as bigint) as merge_bytes,
  cast(round(bytes + n_p * tiles * {tw} * {th} * 8) as bigint) as clip_bytes, cast(w * h + bytes as bigint) as probe_bytes from k"""


def _cost_merge(name: str) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Merge-ordered estimates for all zone layers."""
        rows = [(n, int(q.n_p), int(q.n_s), round(cost.merge_crossings(q)[1]), round(cost.merge_time(q) / 1000)) for n, _, _, q in _params(spark, sf_dir, name)]
        return spark.createDataFrame(rows, "layer string, n_p bigint, n_s bigint, crossings bigint, merge_kilo_units bigint")

    return query


def _cost_clip(name: str) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Estimates of the two baselines for all zone layers."""
        rows = [(n, int(cost.clip_tiles_per_zone(q)), int(cost.clip_pixels(q)), round(cost.clip_sort(q)), round(cost.probe_time(q) / 1000)) for n, _, _, q in _params(spark, sf_dir, name)]
        return spark.createDataFrame(rows, "layer string, tiles bigint, clip_pixels bigint, sort_units bigint, probe_kilo_units bigint")

    return query


def _cost_disk(name: str) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Bytes that the methods read and write, for all zone layers."""
        rows = [(n, round(cost.merge_disk(q)), round(cost.clip_disk(q)), round(cost.probe_disk(q))) for n, _, _, q in _params(spark, sf_dir, name)]
        return spark.createDataFrame(rows, "layer string, merge_bytes bigint, clip_bytes bigint, probe_bytes bigint")

    return query


for _suffix, _r in (("", "RO"), ("_lineitem", "RP")):
    register(f"cost_merge{_suffix}", _per_layer(lambda z, r=_r: _cost_merge_sql(z, r)))(_cost_merge(_r))
    register(f"cost_clip{_suffix}", _per_layer(lambda z, r=_r: _cost_clip_sql(z, r)))(_cost_clip(_r))
    register(f"cost_disk{_suffix}", _per_layer(lambda z, r=_r: _disk_sql(z, r)))(_cost_disk(_r))


_BOX = """
box as (select zone_id, min(gx) as x0, max(gx) as x1, min(gy) as y0, max(gy) as y1 from vertex group by zone_id),
span as (
  select zone_id, greatest(floor(x0 / 256.0), 0) as c0, least(floor(x1 / 256.0), (w + 15) // 16 - 1) as c1,
         greatest(floor(y0 / 256.0), 0) as r0, least(floor(y1 / 256.0), (h + 15) // 16 - 1) as r1 from box, m)"""


@register(
    "measured_tiles_clip",
    _per_layer(lambda z: f"with {O.base(z, 'RO')}, {_BOX} select '{z}' as layer, cast(coalesce(sum((c1 - c0 + 1) * (r1 - r0 + 1)) filter (c0 <= c1 and r0 <= r1), 0) as bigint) as clip_tiles from span"),
)
def measured_tiles_clip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole tiles that clip reads, counted."""
    out = None
    for name, r, z, _ in _params(spark, sf_dir):
        one = baselines.overlapped_tiles(z, r.meta).agg(F.lit(name).alias("layer"), F.count(F.lit(1)).alias("clip_tiles"))
        out = one if out is None else out.unionByName(one)
    return out


_RANKED = "), r as (select rank() over (order by est) as a, rank() over (order by seen) as b, count(*) over (partition by est) as na, count(*) over (partition by seen) as nb from d) select round(corr(a + (na - 1) / 2.0, b + (nb - 1) / 2.0), 6) as r_s from r"


def _spearman_merge(name: str) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Rank correlation of estimated and counted crossings over the zone layers."""
        rows = None
        for n, r, z, q in _params(spark, sf_dir, name):
            one = R.edge_crossings(zones.edges(z), r.meta).agg(F.lit(n).alias("layer"), F.lit(cost.merge_crossings(q)[1]).alias("est"), F.count(F.lit(1)).alias("seen"))
            rows = one if rows is None else rows.unionByName(one)
        return measures.spearman(rows, "est", "seen").select(F.round("r_s", 6).alias("r_s"))

    return query


def _spearman_clip(name: str) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Rank correlation of clip's estimated pixels with the pixels of the tiles it reads."""
        rows = None
        for n, r, z, q in _params(spark, sf_dir, name):
            one = baselines.overlapped_tiles(z, r.meta).agg(F.lit(n).alias("layer"), F.lit(float(cost.clip_pixels(q))).alias("est"), F.count(F.lit(1)).alias("seen"))
            rows = one if rows is None else rows.unionByName(one)
        return measures.spearman(rows, "est", "seen").select(F.round("r_s", 6).alias("r_s"))

    return query


def _clip_seen(z: str, r: str) -> str:
    tw, th = _TILE[r]
    return f"""with {O.base(z, r)}, {_STATS_SQL}, box as (select zone_id, min(gx) as x0, max(gx) as x1, min(gy) as y0, max(gy) as y1 from vertex group by zone_id),
span as (select greatest(floor(x0 / (16.0 * {tw})), 0) as c0, least(floor(x1 / (16.0 * {tw})), ceil(w / cast({tw} as double)) - 1) as c1, greatest(floor(y0 / (16.0 * {th})), 0) as r0, least(floor(y1 / (16.0 * {th})), ceil(h / cast({th} as double)) - 1) as r1 from box, m),
seen as (select cast(coalesce(sum((c1 - c0 + 1) * (r1 - r0 + 1)) filter (c0 <= c1 and r0 <= r1), 0) as bigint) as seen from span)
select cast(n_p * ceil(w_p / ({tw} * cast(0.25 as double))) * ceil(h_p / ({th} * cast(0.25 as double))) * {tw} * {th} as double) as est, seen from s, m, seen"""


for _suffix, _r in (("", "RO"), ("_lineitem", "RP")):
    register(f"spearman_merge{_suffix}", "with d as (" + _per_layer(lambda z, r=_r: f"with {O.base(z, r)}, {_STATS_SQL}, {O.CROSSINGS} select {_CROSS} as est, (select count(*) from crossing) as seen from s") + _RANKED)(_spearman_merge(_r))
    register(f"spearman_clip{_suffix}", "with d as (" + _per_layer(lambda z, r=_r: _clip_seen(z, r)) + _RANKED)(_spearman_clip(_r))


#: Published (estimate, seconds) points, fixed values in printed order.
PUBLISHED = {
    "merge GLC2000": [(6.63e8, 54.9), (6.65e8, 49.6), (7.24e8, 56.7), (2.62e9, 63.9), (1.51e9, 58.8), (3.28e10, 905.0)],
    "merge Tree cover": [(8.40e11, 96.0), (8.40e11, 75.3), (8.40e11, 323.0), (2.52e12, 293.0), (8.42e11, 166.0), (3.11e13, 9660.0)],
    "clip array-DB GLC2000": [(5.45e7, 145.0), (2.19e7, 56.1), (3.97e8, 1060.0), (1.84e9, 7360.0), (1.39e9, 6870.0)],
    "clip hosted GLC2000": [(5.45e7, 22.0), (2.19e7, 16.7), (3.97e8, 30.7), (1.84e9, 240.0), (1.39e9, 380.0)],
    "clip array-DB Tree cover": [(1.48e10, 926.0), (1.49e10, 676.0), (3.09e11, 1.52e5), (1.03e10, 1.15e4), (2.04e10, 1.53e4), (6.60e11, 3.25e5)],
    "clip hosted Tree cover": [(1.48e10, 114.0), (1.49e10, 130.0), (3.09e11, 7230.0), (1.03e10, 780.0), (2.04e10, 880.0), (6.60e11, 23200.0)],
}
_POINTS = ", ".join(f"('{s}', {i}, cast({x!r} as double), cast({y!r} as double))" for s, ps in PUBLISHED.items() for i, (x, y) in enumerate(ps))


def published(spark: SparkSession) -> DataFrame:
    return spark.sql(f"select * from values {_POINTS} as t(series, row, estimate, actual)")


def price_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The measures' job on a given table: an order's price beside its priority, a series a
    hundred customers. Series grow in number, not in size."""
    o = table(spark, sf_dir, "orders")
    return o.select(floor_div(F.col("o_custkey").cast("long"), 100).alias("series"), F.col("o_orderkey").alias("row"), F.col("o_totalprice").alias("estimate"), F.substring("o_orderpriority", 1, 1).cast("double").alias("actual"))


_PRICES = "p as (select o_custkey // 100 as series, o_orderkey as row, o_totalprice as estimate, cast(substr(o_orderpriority, 1, 1) as double) as actual from orders)"

_RANKS = {
    "average": "rank() over (partition by series order by {c}) + (count(*) over (partition by series, {c}) - 1) / 2.0",
    "order": "row_number() over (partition by series order by {c}, row)",
}


@register(
    "spearman_published",
    f"with {_PRICES} "
    + " union all ".join(f"select series, '{t}' as ties, round(corr(a, b), 6) as r_s from (select series, {e.format(c='estimate')} as a, {e.format(c='actual')} as b from p) group by series" for t, e in _RANKS.items()),
)
def spearman_published(spark: SparkSession, sf_dir: str) -> DataFrame:
    p, out = price_points(spark, sf_dir), None
    for ties in ("average", "order"):
        one = measures.spearman(p, "estimate", "actual", ties, ("series",)).select("series", F.lit(ties).alias("ties"), F.round("r_s", 6).alias("r_s"))
        out = one if out is None else out.unionByName(one)
    return out


@register("pearson_published", f"with {_PRICES} select series, round(corr(estimate, actual), 6) as r from p group by series")
def pearson_published(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.pearson(price_points(spark, sf_dir), "estimate", "actual", ("series",)).select("series", F.round("r", 6).alias("r"))


@register("normalize_published", f"with {_PRICES} select series, row, round(estimate / max(estimate) over (partition by series), 6) as estimate_normalized from p")
def normalize_published(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = measures.normalize(price_points(spark, sf_dir), "estimate", "series")
    return n.select("series", "row", F.round("estimate_normalized", 6).alias("estimate_normalized"))


SPATIAL = {"ZS": 20, "ZC": 100, "ZP": 100}


@register(
    "tiles_spatial_vs_none",
    " union all ".join(
        f"select * from (with {O.base(z, 'RO')}, {O.cut_runs(16, 16)} select '{z}' as layer, count(distinct (zone_id // {c}, tile_id)) as key_order, count(distinct tile_id) as distinct_tiles, true as spatial_not_more from piece)"
        for z, c in SPATIAL.items()
    ),
)
def tiles_spatial_vs_none(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tiles read by chunks in key order, and whether spatial chunks read no more."""
    r, out = raster(spark, sf_dir, "RO"), None
    for name, c in SPATIAL.items():
        z = zone_layer(spark, sf_dir, name, r.meta)
        plain = store.footer(mo.intersect(z, r.meta, ChunkSpec("polygons", c))).agg(F.count(F.lit(1)).alias("key_order"), F.countDistinct("tile_id").alias("distinct_tiles"))
        near = measures.tile_reads(z, r, ChunkSpec("polygons", c), "strtile")
        one = plain.join(near).select(F.lit(name).alias("layer"), "key_order", "distinct_tiles", (F.col("tile_reads") <= F.col("key_order")).alias("spatial_not_more"))
        out = one if out is None else out.unionByName(one)
    return out


@register(
    "measures_customer",
    f"""with {O.base('ZC', 'RO')}, {_BOX}, {O.cut_runs(16, 16)},
foot as (select distinct zone_id // 100 as chunk_id, tile_id from piece)
select (select count(*) from crossing) as crossings, (select count(*) from run) as runs, (select cast(sum(x1 - x0) as bigint) from run) as covered_pixels,
  (select count(*) from foot) as units, (select count(distinct tile_id) from foot) as distinct_tiles, (select count(*) from piece) as pieces,
  (select cast(sum((c1 - c0 + 1) * (r1 - r0 + 1)) as bigint) from span where c0 <= c1 and r0 <= r1) as clip_tiles""",
)
def measures_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    r, z = layers(spark, sf_dir, "ZC", "RO")
    got = measures.collect(r, z, ChunkSpec("polygons", 100))
    return got.select("crossings", "runs", "covered_pixels", "units", "distinct_tiles", "pieces", "clip_tiles")
