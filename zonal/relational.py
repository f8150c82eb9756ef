"""Relational operations around the methods: preparing layers and using results.

Each query has SQL beside it; results of zonal statistics enter as a CTE or a DataFrame.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import oracle as O
from .functions import grid
from .functions.arith import floor_div, morton
from .functions.grid import SNAP
from .operators import merge_ordered as mo
from .operators import selection, store, zones
from .operators.baselines import overlapped_tiles
from .operators.zones import ChunkSpec
from .plans import planner
from .plans import sql as surface
from .sources.layers import layers, raster, table, zone_layer
from .workloads import register, tiled

ZS = O.zonal("ZN", "RO")
HIST = f"{O.pairs('ZN', 'RC')}, hist as (select zone_id, v as class, count(*) as cnt from pair group by zone_id, v)"
PIECES = f"{O.base('ZC', 'RO')}, {O.cut_runs(16, 16)}"


def _zs(spark: SparkSession, d: str, zone: str = "ZN", rast: str = "RO") -> DataFrame:
    r, z = layers(spark, d, zone, rast)
    return planner.zonal_stats(r, z, method="merge_ordered")


def _hist(spark: SparkSession, d: str) -> DataFrame:
    r, z = layers(spark, d, "ZN", "RC")
    return planner.zonal_histogram(r, z)


def _named(spark: SparkSession, d: str) -> DataFrame:
    n = table(spark, d, "nation").select(F.col("n_nationkey").cast("long").alias("zone_id"), "n_name", "n_regionkey")
    g = table(spark, d, "region").select(F.col("r_regionkey").alias("n_regionkey"), "r_name")
    return _zs(spark, d).join(F.broadcast(n), "zone_id").join(F.broadcast(g), "n_regionkey")


NAMED = f"named as (select zs.*, n_name, n_regionkey, r_name from zs join nation on zone_id = n_nationkey join region on n_regionkey = r_regionkey)"
WITH_NAMED = f"with zs as ({ZS}), {NAMED}"


@register("rel_pixel_address", f"with {O.base('ZN', 'RO')} select o_orderkey, cast(o_orderkey % w as bigint) as x, cast(o_orderkey // w as bigint) as y, cast(round(o_totalprice * 100) as bigint) as v from orders, m")
def rel_pixel_address(spark, d):
    o = table(spark, d, "orders")
    w, _ = grid.side_lengths(o.count())
    k = F.col("o_orderkey").cast("long")
    return o.select("o_orderkey", F.pmod(k, F.lit(w).cast("long")).alias("x"), floor_div(k, w).alias("y"), F.round(F.col("o_totalprice") * 100).cast("long").alias("v"))


@register("rel_mbr_overlap", f"with {O.base('ZS', 'RO')}, box as (select zone_id, min(gx) as x0, max(gx) as x1, min(gy) as y0, max(gy) as y1 from vertex group by 1) select a.zone_id as a, b.zone_id as b from box a join box b on a.zone_id < b.zone_id and a.x0 <= b.x1 and b.x0 <= a.x1 and a.y0 <= b.y1 and b.y0 <= a.y1")
def rel_mbr_overlap(spark, d):
    """Zones whose boxes overlap: boxes meet in tiles, each pair in its first common tile only."""
    r, z = layers(spark, d, "ZS", "RO")
    m = zones.with_mbr(z).select("zone_id", "mbr")
    far = 64 * SNAP
    cells = m.withColumn("c", F.explode(F.sequence(floor_div(F.col("mbr.x0"), far), floor_div(F.col("mbr.x1"), far))))
    cells = cells.withColumn("r", F.explode(F.sequence(floor_div(F.col("mbr.y0"), far), floor_div(F.col("mbr.y1"), far))))
    a, b = cells.select("c", "r", F.col("zone_id").alias("a"), F.col("mbr").alias("p")), cells.select("c", "r", F.col("zone_id").alias("b"), F.col("mbr").alias("q"))
    met = a.join(b, ["c", "r"]).where("a < b and p.x0 <= q.x1 and q.x0 <= p.x1 and p.y0 <= q.y1 and q.y0 <= p.y1")
    first = (F.col("c") == floor_div(F.greatest("p.x0", "q.x0"), far)) & (F.col("r") == floor_div(F.greatest("p.y0", "q.y0"), far))
    return met.where(first).select("a", "b")


@register("rel_window_filter", "select o_orderkey, o_orderpriority from orders where o_totalprice between 1000 and 100000 and substr(o_orderpriority, 1, 1) in ('1', '2') and o_orderpriority like '%-%' and o_orderdate is not null")
def rel_window_filter(spark, d):
    o = table(spark, d, "orders").where(F.col("o_totalprice").between(1000, 100000) & F.substring("o_orderpriority", 1, 1).isin("1", "2") & F.col("o_orderpriority").like("%-%") & F.col("o_orderdate").isNotNull())
    return o.select("o_orderkey", "o_orderpriority")


@register("rel_zone_names", WITH_NAMED + " select zone_id, n_name, r_name, cnt, sum_v from named")
def rel_zone_names(spark, d):
    return _named(spark, d).select("zone_id", "n_name", "r_name", "cnt", "sum_v")


@register("rel_range_join", f"with {O.pairs('ZN', 'RO')} select zone_id, x, y, v from pair")
def rel_range_join(spark, d):
    r, z = layers(spark, d, "ZN", "RO")
    runs = mo.intersect(z, r.meta, ChunkSpec("none"))
    return selection.range_join(r, runs.drop("chunk_id"), "colocated")


_TILES = "tile as (select distinct (y // 16) * ((w + 15) // 16) + x // 16 as tile_id from px, m)"


def _tiles_of(spark, d, zone):
    r, z = layers(spark, d, zone, "RO")
    return tiled(r).df.select("tile_id"), mo.intersect(z, r.meta, ChunkSpec("none")).select("tile_id")


@register("rel_tiles_semi", f"with {O.base('ZS', 'RO')}, {O.cut_runs(16, 16)}, {_TILES} select tile_id from tile where tile_id in (select tile_id from piece)")
def rel_tiles_semi(spark, d):
    t, p = _tiles_of(spark, d, "ZS")
    return t.join(p, "tile_id", "left_semi")


@register("rel_tiles_pruned", f"with {O.base('ZS', 'RO')}, {O.cut_runs(16, 16)}, {_TILES} select tile_id from tile where tile_id not in (select tile_id from piece)")
def rel_tiles_pruned(spark, d):
    t, p = _tiles_of(spark, d, "ZS")
    return t.join(p, "tile_id", "left_anti")


@register("rel_empty_zones", f"with zs as ({O.zonal('ZP', 'RO')}) select zone_id from zs where cnt = 0")
def rel_empty_zones(spark, d):
    r, z = layers(spark, d, "ZP", "RO")
    return z.df.select("zone_id").join(mo.intersect(z, r.meta, ChunkSpec("none")), "zone_id", "left_anti") if r.meta.pixels == r.df.count() else _zs(spark, d, "ZP").where("cnt = 0").select("zone_id")


@register("rel_full_outer_stats", f"with a as ({O.zonal('ZP', 'RO')}), b as ({O.zonal('ZP', 'RE')}) select coalesce(a.zone_id, b.zone_id) as zone_id, a.sum_v as prices, b.sum_v as signals from (select * from a where cnt > 0) a full join (select * from b where cnt > 0) b on a.zone_id = b.zone_id")
def rel_full_outer_stats(spark, d):
    """Zones that have data in either raster, beside each other."""
    a = _zs(spark, d, "ZP").where("cnt > 0").select("zone_id", F.col("sum_v").alias("prices"))
    b = _zs(spark, d, "ZP", "RE").where("cnt > 0").select("zone_id", F.col("sum_v").alias("signals"))
    return a.join(b, "zone_id", "full")


@register("rel_asof", "select o_orderkey, (select max(event_id) from events e where e.user_id = o.o_custkey and e.event_id <= o.o_orderkey) as event_id from orders o where o_custkey is not null")
def rel_asof(spark, d):
    """The last event of the same customer at or before the order's number: both in one order,
    the last seen carried on, so rows meet without a range join."""
    o = table(spark, d, "orders").where("o_custkey is not null").select(F.col("o_custkey").alias("who"), F.col("o_orderkey").alias("at"), F.lit(1).alias("side"), F.lit(None).cast("long").alias("event"))
    e = table(spark, d, "events").select(F.col("user_id").alias("who"), F.col("event_id").alias("at"), F.lit(0).alias("side"), F.col("event_id").alias("event"))
    w = Window.partitionBy("who").orderBy("at", "side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = o.unionByName(e).withColumn("event_id", F.last("event", ignorenulls=True).over(w))
    return both.where("side = 1").select(F.col("at").alias("o_orderkey"), "event_id")


@register("rel_lateral_rows", f"with {O.base('ZS', 'RO')}, box as (select zone_id, min(gy) as y0, max(gy) as y1 from vertex group by 1) select zone_id, unnest(range(cast(greatest(floor(y0 / 16.0), 0) as bigint), cast(least(floor(y1 / 16.0), h - 1) as bigint) + 1)) as y from box, m")
def rel_lateral_rows(spark, d):
    """Raster rows of each zone's box, by a lateral join with a generator."""
    r, z = layers(spark, d, "ZS", "RO")
    lo, hi = F.greatest(floor_div(F.col("mbr.y0"), SNAP), F.lit(0).cast("long")), F.least(floor_div(F.col("mbr.y1"), SNAP), F.lit(r.meta.rows - 1).cast("long"))
    span = zones.with_mbr(z).select("zone_id", lo.alias("lo"), hi.alias("hi")).where("lo <= hi")
    inner = spark.tvf.explode(F.sequence(F.col("lo").outer(), F.col("hi").outer()))
    return span.lateralJoin(inner).select("zone_id", F.col("col").alias("y"))


@register("rel_tiles_per_zone", f"with {PIECES} select zone_id, count(distinct tile_id) as tiles from piece group by zone_id")
def rel_tiles_per_zone(spark, d):
    r, z = layers(spark, d, "ZC", "RO")
    return mo.intersect(z, r.meta, ChunkSpec("none")).groupBy("zone_id").agg(F.countDistinct("tile_id").alias("tiles"))


@register("rel_rollup_region_nation", WITH_NAMED + " select r_name, n_name, cast(sum(sum_v) as bigint) as sum_v, cast(sum(cnt) as bigint) as cnt from named group by rollup (r_name, n_name)")
def rel_rollup_region_nation(spark, d):
    return _named(spark, d).rollup("r_name", "n_name").agg(F.sum("sum_v").alias("sum_v"), F.sum("cnt").alias("cnt"))


@register("rel_cube_hist", f"with {HIST} select zone_id, class, cast(sum(cnt) as bigint) as cnt from hist group by cube (zone_id, class)")
def rel_cube_hist(spark, d):
    return _hist(spark, d).cube("zone_id", "class").agg(F.sum("cnt").alias("cnt"))


@register("rel_grouping_sets", f"with {HIST} select zone_id, class, cast(sum(cnt) as bigint) as cnt, cast(grouping(zone_id) as bigint) as g from hist group by grouping sets ((zone_id), (class))")
def rel_grouping_sets(spark, d):
    _hist(spark, d).createOrReplaceTempView("zonal_hist")
    return spark.sql("select zone_id, class, sum(cnt) as cnt, cast(grouping(zone_id) as bigint) as g from zonal_hist group by grouping sets ((zone_id), (class))")


@register("rel_hist_pivot", f"with {HIST} select zone_id, " + ", ".join(f"cast(sum(cnt) filter (class = {c}) as bigint) as c{c}" for c in range(1, 6)) + " from hist group by zone_id")
def rel_hist_pivot(spark, d):
    return _hist(spark, d).groupBy("zone_id").pivot("class", [1, 2, 3, 4, 5]).agg(F.sum("cnt")).select("zone_id", *[F.col(str(c)).alias(f"c{c}") for c in range(1, 6)])


@register("rel_rank_zones", f"with zs as ({ZS}) select zone_id, row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr, ntile(4) over w as nt, round(percent_rank() over w, 9) as pr from zs window w as (order by sum_v desc, zone_id)")
def rel_rank_zones(spark, d):
    w = Window.orderBy(F.desc("sum_v"), "zone_id")
    z = _zs(spark, d)
    return z.select("zone_id", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr"), F.ntile(4).over(w).cast("long").alias("nt"), F.round(F.percent_rank().over(w), 9).alias("pr"))


_ROWSUM = f"with {O.base('ZN', 'RO')}, r as (select y, cast(sum(v) as bigint) as s from px group by y)"


def _rows(spark, d):
    return raster(spark, d, "RO").df.groupBy("y").agg(F.sum("v").alias("s"))


@register("rel_lag_rows", _ROWSUM + " select y, s, lag(s) over w as prev, lead(s) over w as next, first_value(s) over w as first, last_value(s) over (order by y rows between unbounded preceding and unbounded following) as last from r window w as (order by y)")
def rel_lag_rows(spark, d):
    w = Window.orderBy("y")
    full = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return _rows(spark, d).select("y", "s", F.lag("s").over(w).alias("prev"), F.lead("s").over(w).alias("next"), F.first("s").over(w).alias("first"), F.last("s").over(full).alias("last"))


@register("rel_running_bytes", f"with {O.base('ZC', 'RO')}, b as (select zone_id, count(*) * 16 + 16 as bytes from vertex group by 1) select zone_id, cast(coalesce(sum(bytes) over (order by zone_id rows between unbounded preceding and 1 preceding), 0) as bigint) as before from b")
def rel_running_bytes(spark, d):
    _, z = layers(spark, d, "ZC", "RO")
    return zones.running_total(zones.with_mbr(z), "zone_id", F.col("bytes"), "before").select("zone_id", "before")


@register("rel_moving_mean_row", _ROWSUM + " select y, cast(sum(s) over (order by y rows between 2 preceding and 2 following) as bigint) as near, cast(sum(s) over (order by y range between 5 preceding and current row) as bigint) as back from r")
def rel_moving_mean_row(spark, d):
    w = Window.orderBy("y")
    return _rows(spark, d).select("y", F.sum("s").over(w.rowsBetween(-2, 2)).alias("near"), F.sum("s").over(w.rangeBetween(-5, 0)).alias("back"))


@register("rel_topk_zones", f"with zs as ({O.zonal('ZC', 'RO')}) select zone_id, sum_v from zs order by sum_v desc nulls last, zone_id limit 10")
def rel_topk_zones(spark, d):
    return _zs(spark, d, "ZC").select("zone_id", "sum_v").orderBy(F.desc_nulls_last("sum_v"), "zone_id").limit(10)


@register("rel_topk_per_region", WITH_NAMED + " select r_name, zone_id, k from (select r_name, zone_id, row_number() over (partition by r_name order by sum_v desc, zone_id) as k from named) where k <= 2")
def rel_topk_per_region(spark, d):
    w = Window.partitionBy("r_name").orderBy(F.desc("sum_v"), "zone_id")
    return _named(spark, d).select("r_name", "zone_id", F.row_number().over(w).cast("long").alias("k")).where("k <= 2")


def _two(op: str) -> str:
    one = lambda z: f"(with {O.base(z, 'RO')}, {O.cut_runs(16, 16)} select distinct tile_id from piece)"
    return f"select tile_id from {one('ZS')} {op} select tile_id from {one('ZB')}"


@register("rel_tiles_union", _two("union"))
def rel_tiles_union(spark, d):
    return _tiles_of(spark, d, "ZS")[1].union(_tiles_of(spark, d, "ZB")[1]).distinct()


@register("rel_tiles_intersect", _two("intersect"))
def rel_tiles_intersect(spark, d):
    return _tiles_of(spark, d, "ZS")[1].intersect(_tiles_of(spark, d, "ZB")[1])


@register("rel_tiles_except", _two("except"))
def rel_tiles_except(spark, d):
    return _tiles_of(spark, d, "ZS")[1].subtract(_tiles_of(spark, d, "ZB")[1])


@register("rel_math", f"with zs as ({ZS}) select zone_id, cast(floor(sum_v / cast(cnt as double)) as bigint) as lo, cast(ceil(sum_v / cast(cnt as double)) as bigint) as hi, sum_v % 97 as m, sum_v // 1000 as k, round(sqrt(cast(cnt as double)), 6) as r, round(log2(cnt), 6) as l, greatest(min_v, 50000) as g, least(max_v, 50000) as s from zs where cnt > 0")
def rel_math(spark, d):
    z = _zs(spark, d).where("cnt > 0")
    mean = F.col("sum_v") / F.col("cnt")
    return z.select("zone_id", F.floor(mean).alias("lo"), F.ceil(mean).alias("hi"), F.pmod("sum_v", F.lit(97).cast("long")).alias("m"), floor_div(F.col("sum_v"), 1000).alias("k"), F.round(F.sqrt("cnt"), 6).alias("r"), F.round(F.log2("cnt"), 6).alias("l"), F.greatest("min_v", F.lit(50000).cast("long")).alias("g"), F.least("max_v", F.lit(50000).cast("long")).alias("s"))


@register("rel_morton", f"with {O.base('ZN', 'RO')}, b as (select x, y, unnest(range(12)) as i from px) select x, y, cast(sum(((x >> i) & 1) << (2 * i)) + sum(((y >> i) & 1) << (2 * i + 1)) as bigint) as code from b group by x, y")
def rel_morton(spark, d):
    return raster(spark, d, "RO").df.select("x", "y", morton(F.col("x"), F.col("y")).alias("code"))


@register("rel_class_code", "select o_orderkey, cast(split_part(o_orderpriority, '-', 1) as integer) as class, regexp_extract(o_orderpriority, '[A-Z].*$') as name, concat_ws('/', substr(o_orderpriority, 1, 1), lower(o_orderpriority)) as tag from orders")
def rel_class_code(spark, d):
    p = F.col("o_orderpriority")
    return table(spark, d, "orders").select("o_orderkey", F.split(p, "-")[0].cast("int").alias("class"), F.regexp_extract(p, "[A-Z].*$", 0).alias("name"), F.concat_ws("/", F.substring(p, 1, 1), F.lower(p)).alias("tag"))


@register("rel_page_hosts", "select lower(regexp_extract(url, '^[a-z]+://([^/]+)', 1)) as host, count(*) as pages, max(length(url)) as longest from pages group by 1")
def rel_page_hosts(spark, d):
    return table(spark, d, "pages").groupBy(F.lower(F.regexp_extract("url", "^[a-z]+://([^/]+)", 1)).alias("host")).agg(F.count(F.lit(1)).alias("pages"), F.max(F.length("url")).cast("long").alias("longest"))


@register("rel_time_band", f"with {O.pairs('ZN', 'RE')} select zone_id, cast(date_diff('day', date '2024-01-01', cast(ts as date)) as bigint) as day, cast(hour(ts) // 6 as bigint) as band, count(*) as cnt, cast(sum(v) as bigint) as sum_v from pair join m on true join events on event_id = y * w + x group by 1, 2, 3")
def rel_time_band(spark, d):
    made = grid.from_key(table(spark, d, "events"), "event_id", F.round(F.col("value") * 100).cast("long"), (32, 32), (F.col("ts"),))
    z = zone_layer(spark, d, "ZN", made.meta)
    got = selection.range_join(made, mo.intersect(z, made.meta, ChunkSpec("none")).drop("chunk_id"))
    day = F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")).cast("long")
    return got.groupBy("zone_id", day.alias("day"), floor_div(F.hour("ts").cast("long"), 6).alias("band")).agg(F.count(F.lit(1)).alias("cnt"), F.sum("v").alias("sum_v"))


@register("rel_tile_roundtrip", f"with {O.base('ZN', 'RO')} select x, y, v from px")
def rel_tile_roundtrip(spark, d):
    return grid.explode_tiles(tiled(raster(spark, d, "RO"))).select("x", "y", "v")


@register("rel_hist_map", f"with {HIST} select zone_id, class, cnt from hist")
def rel_hist_map(spark, d):
    r, z = layers(spark, d, "ZN", "RC")
    return planner.zonal_histogram(r, z, as_map=True).select("zone_id", F.explode("histogram").alias("class", "cnt"))


@register("rel_json_band", "select cast(json_extract_string(props, '$.k') as bigint) // 10 as band, count(*) as cnt, cast(sum(cast(round(value * 100) as bigint)) as bigint) as sum_v from events group by 1")
def rel_json_band(spark, d):
    band = floor_div(F.get_json_object("props", "$.k").cast("long"), 10)
    return table(spark, d, "events").groupBy(band.alias("band")).agg(F.count(F.lit(1)).alias("cnt"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("sum_v"))


@register("rel_nodata", f"with {O.base('ZN', 'RC')}, clean as (select x, y, nullif(v, 5) as v from px), pair as (select zone_id, x, y, v from clean, edge where 16 * y + 8 >= ya and 16 * y + 8 < yb and xa * (yb - ya) + (16 * y + 8 - ya) * (xb - xa) <= (16 * x + 8) * (yb - ya) group by zone_id, x, y, v having count(*) % 2 = 1) select zone.zone_id, count(v) as cnt, cast(sum(v) as bigint) as sum_v, coalesce(max(v), -1) as top, (max(v) is not distinct from 4) as is_four from zone left join pair on pair.zone_id = zone.zone_id group by 1")
def rel_nodata(spark, d):
    r, z = layers(spark, d, "ZN", "RC")
    got = planner.zonal_stats(grid.blank(r, 5), z, method="merge_ordered")
    return got.select("zone_id", "cnt", "sum_v", F.coalesce("max_v", F.lit(-1).cast("long")).alias("top"), F.col("max_v").eqNullSafe(4).alias("is_four"))


@register("rel_approx")
def rel_approx(spark, d):
    """Sketches per zone: approximate median and distinct count, bounded error."""
    r, z = layers(spark, d, "ZN", "RO")
    return planner.zonal_stats(r, z, ("count", "approx_median", "approx_distinct", "mode"), method="merge_ordered")


@register("rel_variance", f"with {O.pairs('ZN', 'RC')} select zone_id, count(*) as cnt, round(var_pop(v), 6) as var_v, round(stddev_pop(v), 6) as stddev_v, bit_or(v) as bits_v, bool_or(v <> 0) as any_v, bool_and(v <> 0) as all_v from pair group by zone_id")
def rel_variance(spark, d):
    r, z = layers(spark, d, "ZN", "RC")
    got = planner.zonal_stats(r, z, ("count", "var", "stddev", "bit_or", "any", "all"), method="merge_ordered", keep_empty=False)
    return got.withColumn("var_v", F.round("var_v", 6)).withColumn("stddev_v", F.round("stddev_v", 6))


@register("rel_layers_many", f"with a as ({ZS}), b as ({O.zonal('ZN', 'RC')}) select 'price' as layer, * from a union all select 'class' as layer, * from b")
def rel_layers_many(spark, d):
    """Two layers on one grid share the runs."""
    r, z = layers(spark, d, "ZN", "RO")
    return mo.zonal_many({"price": r, "class": raster(spark, d, "RC")}, z)


@register("rel_points", f"with {O.base('ZN', 'RO')} select s_suppkey as zone_id, v from supplier, m, px where x = (37 * s_suppkey) % w and y = (61 * s_suppkey) % h")
def rel_points(spark, d):
    r = raster(spark, d, "RO")
    k = F.col("s_suppkey").cast("long")
    gx, gy = F.pmod(37 * k, F.lit(r.meta.cols).cast("long")) * 16 + 3, F.pmod(61 * k, F.lit(r.meta.rows).cast("long")) * 16 + 5
    return r.df.join(zones.points(r.meta, table(spark, d, "supplier"), "s_suppkey", gx, gy), ["x", "y"]).select("zone_id", "v")


@register("rel_clip_footprint", f"with {O.base('ZC', 'RO')}, box as (select zone_id, min(gx) as x0, max(gx) as x1, min(gy) as y0, max(gy) as y1 from vertex group by zone_id), span as (select zone_id, cast(greatest(floor(x0 / 256.0), 0) as bigint) as c0, cast(least(floor(x1 / 256.0), (w + 15) // 16 - 1) as bigint) as c1, cast(greatest(floor(y0 / 256.0), 0) as bigint) as r0, cast(least(floor(y1 / 256.0), (h + 15) // 16 - 1) as bigint) as r1 from box, m) select tile_id, count(*) as readers from (select zone_id, r * ((w + 15) // 16) + c as tile_id from (select *, unnest(range(r0, r1 + 1)) as r from (select *, unnest(range(c0, c1 + 1)) as c from span)), m) group by 1")
def rel_clip_footprint(spark, d):
    """How often clip reads every tile."""
    r, z = layers(spark, d, "ZC", "RO")
    return overlapped_tiles(z, r.meta).groupBy("tile_id").agg(F.count(F.lit(1)).alias("readers"))


_SAMPLED = "md5('3:' || cast(chunk_id as {text}) || ':' || cast(tile_id as {text})) < '8'"


@register("rel_sampled_footer", f"with {O.base('ZC', 'RO')}, {O.cut_runs(16, 16)}, foot as (select zone_id // 500 as chunk_id, tile_id, count(*) as n_runs from piece group by 1, 2) select * from foot where {_SAMPLED.format(text='varchar')}")
def rel_sampled_footer(spark, d):
    """Half of the footer rows by a seeded hash of their key, for partition bounds: reruns agree,
    and every chunk is sampled alike without being listed."""
    r, z = layers(spark, d, "ZC", "RO")
    foot = store.footer(mo.intersect(z, r.meta, ChunkSpec("polygons", 500)))
    return foot.where(_SAMPLED.format(text="string")).select(F.col("chunk_id").cast("long"), "tile_id", "n_runs")



@register("rel_sql_surface", f"with zs as ({ZS}) select zone_id, cnt, sum_v, -180 + cast(cnt + cast(0.5 as double) as double) * cast(0.25 as double) as lon from zs where cnt > 0")
def rel_sql_surface(spark, d):
    """The method as plain SQL over views and SQL functions."""
    r, z = layers(spark, d, "ZN", "RO")
    surface.register_views(spark, r, z, "zv")
    return spark.sql(
        "select zone_id, count(*) as cnt, sum(v) as sum_v, zonal_lon(count(*)) as lon from zv_raster p join zv_runs r "
        "on r.tile_id = zonal_tile_id(p.x, p.y) and r.y = p.y and p.x >= r.x0 and p.x < r.x1 group by zone_id"
    )


@register("rel_table_function", f"with {O.pairs('ZN', 'RO')} select zone_id, x, y, v from pair")
def rel_table_function(spark, d):
    """Pixels of runs by a Python table function, laterally joined."""
    r, z = layers(spark, d, "ZN", "RO")
    surface.register_table_functions(spark)
    runs = mo.intersect(z, r.meta, ChunkSpec("none")).select("zone_id", "tile_id", "y", "x0", "x1")
    s = grid.strips(tiled(r)).select(F.col("tile_id").alias("t"), F.col("y").alias("sy"), "x_off", "values")
    met = runs.join(s, (F.col("t") == F.col("tile_id")) & (F.col("sy") == F.col("y")))
    met = met.select("zone_id", "y", "x0", "x1", F.slice("values", (F.col("x0") - F.col("x_off") + 1).cast("int"), (F.col("x1") - F.col("x0")).cast("int")).alias("vs"))
    met.createOrReplaceTempView("zv_slices")
    return spark.sql("select s.zone_id, f.x, f.y, f.v from zv_slices s, lateral zonal_run_pixels(s.y, s.x0, s.x1, s.vs) f")


@register("rel_pandas_udaf", f"with {O.pairs('ZN', 'RC')} select zone_id, round(sum(cast(v as double) * v) / count(*), 6) as mean_square from pair group by zone_id")
def rel_pandas_udaf(spark, d):
    r, z = layers(spark, d, "ZN", "RC")
    got = surface.grouped_udaf(planner.zone_pairs(r, z), lambda v: (v * v).mean(), "mean_square")
    return got.withColumn("mean_square", F.round("mean_square", 6))
