"""Hand-made cases, invariants, plans and published numbers."""

import math
import random
import re

import pytest
from conftest import DATA
from pyspark.sql import functions as F

from zonal.functions import accumulate, cost, grid, measures
from zonal.functions.cost import STUDY_RASTERS, Params
from zonal.functions.grid import GridMeta, RasterLayer
from zonal.operators import baselines, splits, store, zones
from zonal.operators import merge_ordered as mo
from zonal.operators import runs as R
from zonal.operators.zones import ChunkSpec, ZoneLayer
from zonal.plans import planner
from zonal.sources import formats
from zonal.sources.layers import layers
from zonal.sources.split_source import zonal_from_store

SF = f"{DATA}/sf0.001"


def zone_df(spark, rings_by_zone):
    rows = [(k, [[{"gx": x, "gy": y} for x, y in ring] for ring in rings]) for k, rings in rings_by_zone.items()]
    return ZoneLayer(spark.createDataFrame(rows, f"zone_id bigint, rings {zones.RINGS}"))


def pixel_raster(spark, w, h, tile=(4, 4), value=lambda x, y: 10 * y + x, order="row"):
    px = [(x, y, value(x, y)) for y in range(h) for x in range(w)]
    return RasterLayer(spark.createDataFrame(px, "x bigint, y bigint, v bigint"), GridMeta(h, w, *tile, order=order))


def brute(rings_by_zone, w, h, value=lambda x, y: 10 * y + x):
    out = {}
    for k, rings in rings_by_zone.items():
        got = []
        for y in range(h):
            for x in range(w):
                n, cx, cy = 0, 16 * x + 8, 16 * y + 8
                for ring in rings:
                    for (ax, ay), (bx, by) in zip(ring, ring[1:] + ring[:1]):
                        if ay > by:
                            ax, ay, bx, by = bx, by, ax, ay
                        n += ay <= cy < by and ax * (by - ay) + (cy - ay) * (bx - ax) <= cx * (by - ay)
                if n % 2:
                    got.append(value(x, y))
        out[k] = (len(got), sum(got) if got else None, min(got, default=None), max(got, default=None))
    return out


def answer(df):
    return {r.zone_id: (r.cnt, r.sum_v, r.min_v, r.max_v) for r in df.collect()}


RND = random.Random(3)
CASES = {
    1: [[(0, 0), (160, 0), (160, 160), (0, 160)]],  # around the whole raster
    2: [[(8, 8), (8, 24), (24, 24), (24, 8)]],  # vertices on scan lines and centres
    3: [[(1, 1), (5, 1), (3, 5)]],  # smaller than a pixel, off its centre
    4: [[(6, 6), (11, 6), (8, 11)]],  # smaller than a pixel, on its centre
    5: [[(500, 500), (600, 500), (550, 600)]],  # outside
    6: [[(-50, -20), (90, 40), (20, 190)]],  # partly outside
    7: [[(16, 16), (144, 16), (144, 144), (16, 144)], [(16, 16), (80, 48), (48, 80)]],  # hole touching the ring
    8: [[(0, 0), (80, 80), (160, 0), (160, 160), (80, 80), (0, 160)]],  # touches itself
    9: [[(10, 24), (90, 24), (90, 24), (50, 104)]],  # horizontal edge on a scan line, doubled vertex
    10: [[(8, 8), (72, 72), (8, 136)], [(100, 100), (120, 100), (110, 150)]],
    **{k: [[(RND.randint(-30, 190), RND.randint(-30, 190)) for _ in range(RND.randint(3, 9))]] for k in range(20, 40)},
}


@pytest.mark.parametrize("order", ["row", "col"])
def test_merge_ordered_on_hand_made_zones(spark, order):
    z, want = zone_df(spark, CASES), brute(CASES, 10, 9)
    px = pixel_raster(spark, 10, 9, order=order)
    assert answer(mo.zonal(px, z)) == want
    tiles = grid.tile_pixels(px)
    for reduce in ("hof", "arrow", "pairs"):
        assert answer(mo.zonal(tiles, z, spec=ChunkSpec("polygons", 7), reduce=reduce)) == want


def test_baselines_on_hand_made_zones(spark):
    z, want = zone_df(spark, CASES), brute(CASES, 10, 9)
    px = pixel_raster(spark, 10, 9)
    for run in (baselines.clip, baselines.clip_by_tiles, baselines.pixel_probe, baselines.scanline, baselines.scanline_blackbox):
        assert answer(run(px, z)) == want, run
    assert answer(baselines.clip(px, z, dense=True)) == want
    assert answer(baselines.pixel_probe(px, z, index="kd")) == want
    assert answer(baselines.pixel_probe(px, z, index="none")) == want


def test_tiny_and_empty_rasters(spark):
    square = {1: [[(0, 0), (400, 0), (400, 400), (0, 400)]]}
    for w, h in ((1, 1), (7, 1), (1, 7)):
        assert answer(mo.zonal(pixel_raster(spark, w, h), zone_df(spark, square))) == brute(square, w, h)
    none = RasterLayer(spark.createDataFrame([], "x bigint, y bigint, v bigint"), GridMeta(0, 0))
    assert answer(mo.zonal(none, zone_df(spark, square))) == {1: (0, None, None, None)}
    assert mo.zonal(pixel_raster(spark, 3, 3), ZoneLayer(zone_df(spark, square).df.limit(0))).count() == 0


def test_interior_tiles_are_found(spark):
    square = {1: [[(3, 3), (189, 3), (189, 189), (3, 189)]]}  # 3 by 3 tiles, the middle one has no edge
    r = pixel_raster(spark, 12, 12)
    units = {x.tile_id for x in store.footer(mo.intersect(zone_df(spark, square), r.meta)).collect()}
    assert units == set(range(9)) and answer(mo.zonal(grid.tile_pixels(r), zone_df(spark, square))) == brute(square, 12, 12)


def test_sparse_tiles_keep_positions(spark):
    px = spark.createDataFrame([(1, 0, 5), (3, 2, 7), (9, 8, 1)], "x bigint, y bigint, v bigint")
    for cells in (4096, 1):
        old, grid.MAP_CELLS = grid.MAP_CELLS, cells
        try:
            back = grid.explode_tiles(grid.tile_pixels(RasterLayer(px, GridMeta(9, 10, 4, 4)))).select("x", "y", "v").collect()
        finally:
            grid.MAP_CELLS = old
        assert sorted(map(tuple, back)) == [(1, 0, 5), (3, 2, 7), (9, 8, 1)]


def test_disjoint_cover_counts_every_pixel_once(spark):
    r, z = layers(spark, SF, "ZN", "RO")
    got = answer(planner.zonal_stats(r, z, method="merge_ordered"))
    assert sum(v[0] for v in got.values()) == 1500 and sum(v[1] for v in got.values()) == r.df.agg(F.sum("v")).first()[0]
    odd = R.edge_crossings(zones.edges(z), r.meta).groupBy("zone_id", "y").count().where("count % 2 = 1")
    assert odd.count() == 0


def test_no_exchange_above_the_raster(spark):
    r, z = layers(spark, SF, "ZN", "RO")
    plan = planner.explain_zonal(r, z, method="merge_ordered", strategy="broadcast_runs").tree
    assert "BroadcastHashJoin" in plan
    scan = plan.index("orders.parquet")
    assert "o_totalprice" in plan[scan:] and "o_comment" not in plan
    logical = planner.zonal_stats(r, z, method="merge_ordered", strategy="broadcast_runs", keep_empty=False)._jdf.queryExecution().executedPlan().toString()
    lines = [x for x in logical.split("\n") if re.search(r"HashAggregate|Exchange|Join|Scan", x)]
    top = [re.search(r"(HashAggregate|BroadcastExchange|Exchange|BroadcastHashJoin|Scan)", x)[1] for x in lines]
    assert top[:4] == ["HashAggregate", "Exchange", "HashAggregate", "BroadcastHashJoin"]  # partial right over the join


def test_splits_cover_touched_tiles_once(spark):
    r, z = layers(spark, SF, "ZC", "RO")
    foot = store.footer(mo.intersect(z, r.meta, ChunkSpec("polygons", 40))).cache()
    want = sorted((x.chunk_id, x.tile_id) for x in foot.collect())
    for mode in ("islands", "blocks"):
        units = splits.expand(splits.plan(foot, r.meta, 3, mode=mode), foot)
        assert sorted((x.chunk_id, x.tile_id) for x in units.collect()) == want
    assert splits.balance(splits.plan(foot, r.meta, 3)).first().imbalance >= 1


def test_store_and_split_source(spark, tmp_path):
    r, z = layers(spark, SF, "ZC", "RO")
    tiles = grid.tile_pixels(r)
    want = {k: v for k, v in answer(planner.zonal_stats(r, z, method="merge_ordered")).items() if v[0]}
    formats.write_tiles(tiles, f"file://{tmp_path}/tiles", 8)
    written = formats.read_tiles(spark, f"file://{tmp_path}/tiles", r.meta, 8)
    assert written.df.count() == tiles.df.count()
    store.write(mo.intersect(z, r.meta, ChunkSpec("polygons", 40)), f"file://{tmp_path}/s")
    assert answer(zonal_from_store(spark, written, f"file://{tmp_path}/s", 3)) == want
    store.write(mo.intersect(z, r.meta), f"file://{tmp_path}/d", "gzip", drop_tile_id=True)
    assert store.read(spark, f"file://{tmp_path}/d", r.meta).select("tile_id").distinct().count() == store.read_footer(spark, f"file://{tmp_path}/d").select("tile_id").distinct().count()
    sizes = measures.store_sizes(r, z, f"file://{tmp_path}/c")
    assert measures.compression_ratio(sizes["none"], sizes["gzip"]) > 1


def test_custom_accumulator_equals_native(spark):
    class SumOfSquares:
        columns = "n bigint, squares bigint"

        def init(self):
            return 0, 0

        def update_many(self, state, values):
            return state[0] + len(values), state[1] + int((values.astype(object) ** 2).sum())

        def merge(self, a, b):
            return a[0] + b[0], a[1] + b[1]

        def finish(self, state):
            return state

    r, z = layers(spark, SF, "ZN", "RC")
    got = {x.zone_id: (x.n, x.squares) for x in planner.zonal_custom(r, z, SumOfSquares()).collect()}
    want = planner.zone_pairs(r, z).groupBy("zone_id").agg(F.count("v").alias("n"), F.sum(F.col("v") * F.col("v")).alias("s"))
    assert got == {x.zone_id: (x.n, x.s) for x in want.collect()}


def test_formats_round_trip(spark):
    z = zone_df(spark, {k: CASES[k] for k in (1, 7)})
    rings = {r.zone_id: r.rings for r in z.df.collect()}
    assert {r.zone_id: r.rings for r in formats.from_wkb(formats.to_wkb(z), "zone_id", "wkb").df.collect()} == rings
    wkt = formats.from_wkt(formats.to_wkt(z), "zone_id", "wkt")
    px = pixel_raster(spark, 10, 9)
    assert answer(mo.zonal(px, wkt)) == answer(mo.zonal(px, z))
    gj = spark.createDataFrame([(1, '{"type":"Polygon","coordinates":[[[0,0],[160,0],[160,160],[0,160],[0,0]]]}')], "k bigint, g string")
    assert answer(mo.zonal(px, formats.from_geojson(gj, "k", "g")))[1] == brute({1: CASES[1]}, 10, 9)[1]


def test_interpolation_conserves_counts(spark):
    r, src = layers(spark, SF, "ZN", "RC")
    _, tgt = layers(spark, SF, "ZR", "RC")
    counts = src.df.select("zone_id", (F.col("zone_id") * 7 + 1).alias("population"))
    total = sum(x.estimate for x in planner.areal_interpolate(src, tgt, r, counts, {1: 5, 2: 4, 3: 3, 4: 2, 5: 1}).collect())
    assert total == pytest.approx(sum(7 * k + 1 for k in range(25)))


def test_points_and_lines(spark):
    meta = GridMeta(9, 10)
    line = zone_df(spark, {1: [[(8, 8), (72, 8)]], 2: [[(8, 8), (8, 40), (40, 40)]]})
    got = sorted(map(tuple, zones.lines(meta, line).select("zone_id", "x", "y").collect()))
    assert got == [(1, 0, 0), (1, 1, 0), (1, 2, 0), (1, 3, 0), (1, 4, 0), (2, 0, 0), (2, 0, 1), (2, 0, 2), (2, 1, 2), (2, 2, 2)]


def test_curves_and_partitions(spark):
    from zonal.functions.arith import hilbert

    codes = spark.range(256).select((F.col("id") % 16).alias("x"), F.floor(F.col("id") / 16).alias("y"))
    path = [(r.x, r.y) for r in codes.withColumn("h", hilbert(F.col("x"), F.col("y"), 4)).orderBy("h").collect()]
    assert all(abs(a[0] - b[0]) + abs(a[1] - b[1]) == 1 for a, b in zip(path, path[1:]))
    r, z = layers(spark, SF, "ZC", "RO")
    for kind in ("strtile", "zorder", "hilbert"):
        per = zones.partition_spatial(zones.with_mbr(z), kind, 30).groupBy("chunk_id").count().collect()
        assert len(per) > 2 and max(x["count"] for x in per) < 75


# ---- published numbers


def test_tile_counts_of_the_study():
    def q(rast, w, h):
        c, r, w_t, h_t, p = STUDY_RASTERS[rast]
        return Params(r, c, w_t, h_t, p, 49, 165_186, w, h)

    assert cost.clip_pixels(q("GLC2000", 10, 5)) == 49 * 45 * 128 * 128
    assert cost.probe_disk(q("MERIS", 1, 1)) == 8_398_080_000
    one = Params(100, 100, 10, 10, 1.0, 4, 32, 8, 6)
    assert one.mean_segments == 8 and cost.clip_sort(one) == 96 and cost.clip_tiles_per_zone(one) == 1 and cost.clip_time(one) == 496
    assert cost.segment_height(one) == 1.5 and cost.segment_height(one, "printed") == 0.375
    assert cost.merge_crossings(one) == (48, 48) and cost.merge_intersect(one) == pytest.approx(48 + 48 * math.log2(48))
    assert cost.merge_select(one, 25, 10) == 300 and cost.probe_time(one) == 32 * 5 + 10_000 * 5


def test_published_rank_correlations(spark):
    from zonal.workloads import published

    got = {(r.series, t): round(r.r_s, 6) for t in ("average", "order") for r in measures.spearman(published(spark), "estimate", "actual", t, ("series",)).collect()}
    assert got["merge GLC2000", "average"] == pytest.approx(0.942857, abs=1e-6)
    assert got["merge Tree cover", "average"] == pytest.approx(0.638, abs=1e-3) and got["merge Tree cover", "order"] == pytest.approx(0.771, abs=1e-3)
    assert got["clip array-DB GLC2000", "average"] == 1 and got["clip hosted GLC2000", "average"] == pytest.approx(0.9)
    assert got["clip array-DB Tree cover", "average"] == pytest.approx(0.771, abs=1e-3) and got["clip hosted Tree cover", "average"] == pytest.approx(0.829, abs=1e-3)


def test_measured_trends(spark):
    """Clip reads more tiles than chunks in key order, those more than spatial chunks."""
    r, z = layers(spark, f"{DATA}/sf0.01", "ZC", "RO")
    clip = baselines.overlapped_tiles(z, r.meta).count()
    plain = measures.tile_reads(z, r, ChunkSpec("polygons", 100)).first()[0]
    near = measures.tile_reads(z, r, ChunkSpec("polygons", 100), "strtile").first()[0]
    assert clip > plain > near >= 64 and plain == 946
    q = Params.from_data(r.meta, z)
    assert cost.merge_crossings(q)[1] == pytest.approx(R.edge_crossings(zones.edges(z), r.meta, False).count(), rel=0.05)


def test_planner_prefers_scanline_for_small_inputs():
    small = Params(100, 100, 16, 16, 0.25, 10, 100, 1, 1)
    large = Params(600_000, 1_200_000, 256, 256, 0.0003, 1e7, 3e8, 0.1, 0.1)
    assert planner.choose(small, 8) == "scanline" and planner.choose(large, 8) == "merge_ordered"
    assert planner.strategy_for(small) == "broadcast_runs" and planner.strategy_for(large) == "colocated"
    assert measures.speedup(4, 2) == 2 and measures.ingest(None) == 0 and measures.repeat(lambda: 1, 2) >= 0


def test_histogram_bins(spark):
    r, z = layers(spark, SF, "ZN", "RO")
    lo, hi = r.df.agg(F.min("v"), F.max("v")).first()
    got = planner.zonal_histogram(r, z, (lo, hi + 1, 4))
    assert got.agg(F.sum("cnt")).first()[0] == 1500 and {x[0] for x in got.select("class").distinct().collect()} <= {1, 2, 3, 4}
    assert accumulate.histogram(planner.zone_pairs(r, z).limit(0)).count() == 0


def test_measures_read_a_given_table(spark):
    """They once had only the published points, which no table held."""
    from zonal.workloads import QUERIES

    for name in ("spearman_published", "pearson_published", "normalize_published"):
        assert any(f.endswith("orders.parquet") for f in QUERIES[name](spark, SF).inputFiles())
