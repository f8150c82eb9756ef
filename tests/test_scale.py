"""Plans, guards and laws: what has to hold at any size."""

import math
import re

import numpy as np
import pytest
from conftest import DATA
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from test_zonal import CASES, answer, brute, pixel_raster, zone_df

from zonal import workloads
from zonal.functions import accumulate, cost, grid
from zonal.functions.cost import STUDY_RASTERS, Params
from zonal.functions.grid import GridMeta, RasterLayer
from zonal.operators import baselines, selection, splits, store, zones
from zonal.operators import merge_ordered as mo
from zonal.operators.zones import ChunkSpec, ZoneLayer
from zonal.plans import planner
from zonal.sources import formats
from zonal.sources.layers import layers
from zonal.sources.split_source import ZonalSplitReader

SF = f"{DATA}/sf0.001"


def tree(df):
    return df._jdf.queryExecution().executedPlan().toString()


# ---- plans


def test_a_bucketed_raster_is_not_exchanged(spark, tmp_path):
    r, z = layers(spark, SF, "ZC", "RO")
    tiles = formats.write_bucketed(grid.tile_pixels(r), f"zonal_plan_{tmp_path.name.replace('-', '_')}", path=f"file://{tmp_path}/t")
    plan = tree(planner.zonal_stats(tiles, z, method="merge_ordered", strategy="colocated", keep_empty=False))
    assert plan.count("Bucketed: true") == 1 and plan.count("FileScan parquet spark_catalog") == 1
    lines = plan.split("\n")
    at = next(i for i, x in enumerate(lines) if "Bucketed: true" in x)
    depth = lambda x: len(re.match(r"[\s:|+\-*()\d]*", x)[0])
    above, level = [], depth(lines[at])
    for x in reversed(lines[:at]):  # the scan's own ancestors, up to its join
        if depth(x) < level:
            level = depth(x)
            above.append(x)
            if "Join" in x:
                break
    assert "SortMergeJoin" in above[-1] and not any("Exchange" in x for x in above)


def test_directories_without_a_run_are_not_read(spark, tmp_path):
    square = zone_df(spark, {1: [[(70, 70), (100, 70), (100, 100), (70, 100)]]})
    r = pixel_raster(spark, 40, 40)
    formats.write_tiles(grid.tile_pixels(r), f"file://{tmp_path}/t", 5)
    tiles = formats.read_tiles(spark, f"file://{tmp_path}/t", r.meta, 5)
    got = planner.zonal_stats(tiles, square, method="merge_ordered", keep_empty=False)
    assert "tile_group" in re.search(r"PartitionFilters: \[([^\]]*)\]", tree(got))[1]
    assert answer(got) == brute({1: [[(70, 70), (100, 70), (100, 100), (70, 100)]]}, 40, 40)
    touched = {f.split("tile_group=")[1].split("/")[0] for f in selection.pruned(tiles, selection.work_units(mo.intersect(square, r.meta))).df.inputFiles()}
    assert 0 < len(touched) <= 20
    scan = selection.pruned(tiles, selection.work_units(mo.intersect(square, r.meta))).df
    assert {x[0] for x in scan.select("tile_group").distinct().collect()} == {x[0] for x in mo.intersect(square, r.meta).select(F.floor(F.col("tile_id") / 5)).distinct().collect()}


def test_tiles_are_scanned_once_and_pairs_are_not_stored(spark, tmp_path):
    r, z = layers(spark, SF, "ZC", "RO")
    formats.write_tiles(grid.tile_pixels(r), f"file://{tmp_path}/t", 8)
    tiles = formats.read_tiles(spark, f"file://{tmp_path}/t", r.meta)
    for reduce in ("hof", "arrow", "pairs"):
        plan = tree(planner.zonal_stats(tiles, z, method="merge_ordered", strategy="broadcast_runs", reduce=reduce, keep_empty=False))
        assert plan.count(f"{tmp_path}/t") == 1
        top = [re.search(r"(HashAggregate|BroadcastExchange|Exchange|BroadcastHashJoin|Scan)", x)[1] for x in plan.split("\n") if re.search(r"HashAggregate|Exchange|Join|Scan", x)]
        assert top[:4] == ["HashAggregate", "Exchange", "HashAggregate", "BroadcastHashJoin"], reduce


def test_nothing_is_broadcast_unmeasured(spark, monkeypatch):
    r, z = layers(spark, SF, "ZN", "RO")
    assert "strategy=broadcast" in mo.zonal(r, z)._jdf.queryExecution().analyzed().toString()
    monkeypatch.setattr(selection, "BROADCAST_RUNS", 4)
    monkeypatch.setattr(baselines, "BROADCAST_EDGES", 4)
    for df in (mo.zonal(r, z), planner.zone_pairs(r, z), mo.zonal_many({"a": r}, z), baselines.fused(r, z, "hof"), baselines.pixel_probe(r, z)):
        assert "strategy=broadcast" not in df._jdf.queryExecution().analyzed().toString()
    with pytest.raises(ValueError, match="without an index"):
        baselines.pixel_probe(r, z, index="none")
    with pytest.raises(ValueError, match="unknown strategy"):
        mo.zonal(r, z, strategy="everywhere")


# ---- splits


def test_splits_of_some_tiles_and_one_file(spark, tmp_path):
    r, z = layers(spark, SF, "ZC", "RO")
    store.write(mo.intersect(z, r.meta, ChunkSpec("polygons", 40)), f"file://{tmp_path}/s", meta=r.meta)
    made = {}
    for per, one in ((1, 0), (3, 0), (64, 0), (64, 2)):
        reader = ZonalSplitReader({"tiles": "", "store": f"file://{tmp_path}/s", "tile_w": 16, "tile_h": 16, "tiles_x": r.meta.tiles_x, "tiles_per_split": str(per), "tiles_per_file": str(one)})
        made[per, one] = reader.partitions()
    units = store.read_footer(spark, f"file://{tmp_path}/s").count()
    assert len(made[1, 0]) == units > len(made[3, 0]) > len(made[64, 0])
    assert all(p.hi - p.lo < 3 for p in made[3, 0]) and all(p.lo // 2 == p.hi // 2 for p in made[64, 2])
    assert splits.balance(splits.plan(store.read_footer(spark, f"file://{tmp_path}/s"), r.meta, 1)).first().imbalance == 1


def test_store_reads_chosen_chunks_only(spark, tmp_path):
    r, z = layers(spark, SF, "ZC", "RO")
    runs = mo.intersect(z, r.meta, ChunkSpec("polygons", 40))
    store.write(runs, f"file://{tmp_path}/s", meta=r.meta)
    some = store.read(spark, f"file://{tmp_path}/s", r.meta, [1, 2])
    assert {x[0] for x in some.select("chunk_id").distinct().collect()} == {1, 2} and some.count() == runs.where("chunk_id in (1, 2)").count()
    assert "chunk_id" in re.search(r"PartitionFilters: \[([^\]]*)\]", tree(some))[1]


# ---- measurements of other kinds


@pytest.mark.parametrize("kind", ["int", "float", "double", "decimal(12,2)"])
def test_types_and_nodata(spark, kind):
    z, want = zone_df(spark, CASES), brute(CASES, 10, 9, lambda x, y: (10 * y + x) * 2 + 1)
    px = pixel_raster(spark, 10, 9, value=lambda x, y: (10 * y + x) * 2 + 1)
    half = 1 if kind == "int" else 2
    df = px.df.withColumn("v", (F.col("v") / half).cast(kind))
    r = RasterLayer(df, px.meta)
    tiles = grid.tile_pixels(r)
    runs = {
        "pixels": lambda: mo.zonal(r, z), "hof": lambda: mo.zonal(tiles, z), "pairs": lambda: mo.zonal(tiles, z, reduce="pairs"), "clip": lambda: baselines.clip(r, z),
        "tiles": lambda: baselines.clip_by_tiles(r, z), "probe": lambda: baselines.pixel_probe(r, z), "auto": lambda: planner.zonal_stats(r, z),
    }
    if not kind.startswith("decimal"):
        runs |= {"arrow": lambda: mo.zonal(tiles, z, reduce="arrow"), "scanline": lambda: baselines.scanline(r, z)}
    number = lambda x: None if x is None else float(x) * half
    for name, run in runs.items():
        got = {k: (n, *map(number, rest)) for k, (n, *rest) in answer(run()).items()}
        assert got == {k: (n, *map(lambda x: None if x is None else float(x), rest)) for k, (n, *rest) in want.items()}, name
    if kind in ("float", "double"):
        with pytest.raises(ValueError, match="bins"):
            planner.zonal_histogram(r, z)
        with pytest.raises(ValueError, match="bit_or"):
            mo.zonal(r, z, ("bit_or",))


def test_nan_stays_in_its_zone(spark):
    px = spark.createDataFrame([(x, 0, float("nan") if x == 1 else float(x)) for x in range(6)], "x bigint, y bigint, v double")
    z = zone_df(spark, {1: [[(0, 0), (48, 0), (48, 16), (0, 16)]], 2: [[(48, 0), (96, 0), (96, 16), (48, 16)]]})
    tiles = grid.tile_pixels(RasterLayer(px, GridMeta(1, 6, 6, 1)))
    for reduce in ("hof", "arrow", "pairs"):
        got = answer(mo.zonal(tiles, z, reduce=reduce))
        assert math.isnan(got[1][1]) and got[2] == (3, 12.0, 3.0, 5.0), reduce


# ---- laws


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(-1000, 1000), max_size=30), st.lists(st.integers(-1000, 1000), max_size=30), st.lists(st.integers(-1000, 1000), max_size=30))
def test_accumulator_laws(a, b, c):
    acc = workloads.SquareSum()
    x, y, z = (acc.update_many(acc.init(), np.array(v, np.int64)) for v in (a, b, c))
    assert acc.merge(x, y) == acc.merge(y, x) and acc.merge(x, acc.merge(y, z)) == acc.merge(acc.merge(x, y), z)
    assert acc.merge(acc.init(), x) == x and acc.update_many(x, np.array(b, np.int64)) == acc.merge(x, y)


def test_answers_do_not_depend_on_partitions(spark):
    r, z = layers(spark, SF, "ZC", "RO")
    old, seen = spark.conf.get("spark.sql.shuffle.partitions"), []
    try:
        for n in ("3", "8", "29"):
            spark.conf.set("spark.sql.shuffle.partitions", n)
            seen += [answer(planner.zonal_stats(r.__class__(r.df.repartition(int(n)), r.meta), z, method=m)) for m in ("merge_ordered", "clip")]
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", old)
    assert all(x == seen[0] for x in seen)


def test_scalar_function_agrees_on_containment(spark):
    """A row-at-a-time Python function as reference for the plan's own predicate."""

    def contains(rings, x, y):
        n, cx, cy = 0, 16 * x + 8, 16 * y + 8
        for ring in rings:
            for a, b in zip(ring, ring[1:] + ring[:1], strict=True):
                (ax, ay), (bx, by) = (a, b) if a[1] <= b[1] else (b, a)
                n += ay <= cy < by and ax * (by - ay) + (cy - ay) * (bx - ax) <= cx * (by - ay)
        return n % 2 == 1

    inside = F.udf(contains, "boolean")
    z = zone_df(spark, {k: CASES[k] for k in (2, 7, 21)})
    cells = spark.range(90).select((F.col("id") % 10).alias("x"), F.floor(F.col("id") / 10).alias("y"))
    both = z.df.join(zones.edge_arrays(z).select("zone_id", "edges"), "zone_id").crossJoin(cells)
    wrong = both.where(inside("rings", F.col("x").cast("int"), F.col("y").cast("int")) != zones.contains(F.col("edges"), F.col("x"), F.col("y")))
    assert wrong.count() == 0


def test_tiles_of_the_study():
    """Hand calculation on printed sizes: mean extents of the states, in degrees."""
    for name, tiles in (("GLC2000", 44), ("Tree cover", 30_572)):
        c, r, w_t, h_t, p = STUDY_RASTERS[name]
        assert cost.clip_tiles_per_zone(Params(r, c, w_t, h_t, p, 49, 165_000, 12.18, 4.28)) == tiles


def test_approximate_statistics_are_near(spark):
    r, z = layers(spark, f"{DATA}/sf0.01", "ZN", "RO")
    got = {x.zone_id: x for x in planner.zonal_stats(r, z, ("count", "approx_median", "approx_distinct", "mode", "kll", "hll"), method="merge_ordered").collect()}
    values = {}
    for x in planner.zone_pairs(r, z).collect():
        values.setdefault(x.zone_id, []).append(x.v)
    for k, vs in values.items():
        vs.sort()
        rank = np.searchsorted(vs, got[k].median_v) / len(vs)
        assert abs(rank - 0.5) < 0.02 and abs(got[k].distinct_v / len(set(vs)) - 1) < 0.2
        assert vs.count(got[k].mode_v) == max(map(vs.count, set(vs)))
    sketches = spark.createDataFrame([(k, x.kll_v, x.hll_v) for k, x in got.items()], "k bigint, q binary, h binary")
    for x in sketches.select("k", F.expr("kll_sketch_get_quantile_bigint(q, 0.5D)").alias("m"), F.expr("hll_sketch_estimate(h)").alias("d")).collect():
        assert abs(np.searchsorted(values[x.k], x.m) / len(values[x.k]) - 0.5) < 0.05 and abs(x.d / len(set(values[x.k])) - 1) < 0.1


# ---- formats


def test_tiled_binary_files(spark, tmp_path):
    values = [[(t * 100 + i) for i in range(12)] for t in range(6)]
    for n in range(2):
        (tmp_path / f"r{n}.bin").write_bytes(formats.to_tiled_binary(7, 8, 4, 3, 2, [[v + n for v in t] for t in values]))
    r = formats.read_tiled_binary(spark, f"file://{tmp_path}/*.bin", nodata=105)
    assert (r.meta.cols, r.meta.rows, r.meta.tiles_x, r.meta.tiles_y) == (7, 8, 2, 3)
    cells = {(x.file_id, x.x, x.y): x.v for x in grid.explode_tiles(r).collect()}
    want = {(n, x, y): values[y // 3 * 2 + x // 4][y % 3 * 4 + x % 4] + n for n in range(2) for x in range(7) for y in range(8)}
    assert cells == {k: v for k, v in want.items() if v != 105}
    one = RasterLayer(r.df.where("file_id = 0"), r.meta, "tiles")
    square = [[(0, 0), (112, 0), (112, 128), (0, 128)]]
    assert answer(mo.zonal(one, zone_df(spark, {1: square})))[1][0] == sum(1 for (n, *_), v in want.items() if n == 0 and v != 105)
    (tmp_path / "bad.bin").write_bytes(b"nothing")
    with pytest.raises(ValueError, match="no tiled raster"):
        formats.read_tiled_binary(spark, f"file://{tmp_path}/bad.bin")


@pytest.mark.parametrize("kind", ["parquet", "orc", "json", "csv", "text"])
def test_results_in_any_format(spark, tmp_path, kind):
    r, z = layers(spark, SF, "ZR", "RC")
    out = planner.zonal_histogram(r, z, as_map=True).withColumn("n", F.lit(1).cast("long"))
    formats.write_table(out, f"file://{tmp_path}/o", kind)
    back = spark.read.option("header", "true").format(kind).load(f"file://{tmp_path}/o")
    assert back.count() == 5 and (kind == "text" or {"zone_id", "histogram", "n"} == set(back.columns))
    with pytest.raises(ValueError, match="unknown format"):
        formats.write_table(out, f"file://{tmp_path}/p", "xml")
