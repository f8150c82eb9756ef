"""Zones explode to far more rows than Spark expects of their table; none of these may be broadcast."""

from conftest import DATA

from zonal.operators import baselines
from zonal.sources.layers import layers

SF = f"{DATA}/sf0.001"


def planned(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_a_dense_mask_is_not_broadcast(spark):
    r, z = layers(spark, SF, "ZN", "RO")
    assert "Broadcast" not in planned(baselines.mask(z, r.meta, dense=True))


def test_runs_of_tiles_are_not_broadcast(spark):
    r, z = layers(spark, SF, "ZC", "RO")
    assert "Broadcast" not in planned(baselines.clip_by_tiles(r, z, empty=False))


def test_a_kd_index_grows_with_its_layer(spark, monkeypatch):
    """A fixed number of leaves met every pixel with a 64th of all zones."""
    from pyspark.sql import functions as F

    r, z = layers(spark, SF, "ZC", "RO")
    monkeypatch.setattr(baselines, "LEAF_ZONES", 1)
    index, tree = baselines.probe_index(z, r.meta, "kd")
    assert 1 << tree.depth >= z.df.count() > 64
    boxes = [(b.zone_id, b.mbr) for b in baselines.zones.with_mbr(z).collect()]
    leaf = {(p.x, p.y): p.c for p in r.df.select("x", "y", tree.leaf(F.col("x") * 16 + 8, F.col("y") * 16 + 8).alias("c")).collect()}
    cells = {(i.zone_id, i.cell) for i in index.select("zone_id", "cell").collect()}
    assert len(cells) < 40 * len(boxes)
    for (x, y), c in leaf.items():
        for zone, b in boxes:
            if b.x0 <= 16 * x + 8 <= b.x1 and b.y0 <= 16 * y + 8 <= b.y1:
                assert (zone, c) in cells
    want, got = (sorted(map(tuple, baselines.pixel_probe(r, z, index=k).collect())) for k in ("grid", "kd"))
    assert want == got


def test_parts_do_not_grow_the_plan(spark):
    """A plan a part: 208 of them for 1,000 suppliers, each with its own pass over the raster."""
    r, z = layers(spark, SF, "ZC", "RO")
    for method in (baselines.merge_parts, baselines.clip_parts):
        few, many = (baselines.run_in_parts(r, z, size, method) for size in (1 << 40, 300))
        assert planned(few).count("FileScan") == planned(many).count("FileScan") < 12
        assert sorted(map(tuple, few.collect())) == sorted(map(tuple, many.collect())) == sorted(map(tuple, baselines.clip(r, z).collect()))
