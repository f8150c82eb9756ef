"""Streams end in the batch's answer; late rows are dropped; repeats count once."""

import datetime as dt

import pytest
from conftest import DATA
from pyspark.sql import functions as F

from zonal.functions.grid import from_key
from zonal.operators.zones import ZoneLayer
from zonal.plans import planner
from zonal.sources.layers import zone_layer
from zonal.streaming import pixels as P

SF = f"{DATA}/sf0.001"


@pytest.fixture(scope="module")
def parts(spark, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("events"))
    ev = spark.read.parquet(f"{SF}/events.parquet")
    ev.repartition(2).write.mode("overwrite").parquet(folder)
    meta = from_key(ev, "event_id", F.lit(0), (32, 32)).meta
    return folder, ev, meta, zone_layer(spark, SF, "ZN", meta)


def test_running_statistics_end_as_batch(spark, parts, tmp_path):
    folder, ev, meta, z = parts
    px = P.event_pixels(P.source(spark, folder, ev.schema), meta)
    P.to_table(P.running_stats(px, z, meta), "running", str(tmp_path), "complete").awaitTermination(120)
    raster = from_key(ev, "event_id", F.round(F.col("value") * 100).cast("long"), (32, 32))
    want = planner.zonal_stats(raster, z, method="merge_ordered", keep_empty=False)
    cols = ["zone_id", "cnt", "sum_v", "min_v", "max_v"]
    assert sorted(map(tuple, spark.table("running").select(cols).collect())) == sorted(map(tuple, want.select(cols).collect()))


def test_late_and_repeated_rows(spark, tmp_path):
    day = dt.datetime(2024, 1, 1)
    schema = "event_id bigint, ts timestamp, value double"
    batches = [
        [(0, day, 1.0), (0, day, 1.0), (1, day + dt.timedelta(days=3), 2.0)],
        [(2, day + dt.timedelta(hours=1), 4.0)],  # days behind the watermark
        [(3, day + dt.timedelta(days=9), 8.0)],
    ]
    square = ZoneLayer(spark.createDataFrame([(1, [[{"gx": 0, "gy": 0}, {"gx": 64, "gy": 0}, {"gx": 64, "gy": 64}, {"gx": 0, "gy": 64}]])], "zone_id bigint, rings array<array<struct<gx:bigint,gy:bigint>>>"))
    from zonal.functions.grid import GridMeta

    meta = GridMeta(2, 2)
    for i, rows in enumerate(batches):
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
        stream = P.without_repeats(P.event_pixels(P.source(spark, f"{tmp_path}/in", spark.createDataFrame([], schema).schema), meta))
        got = P.windowed(P.zone_stream(stream, square, meta), "1 day", delay=None)
        kept = []
        P.to_batches(got, lambda df, _: kept.extend(df.collect()), f"{tmp_path}/c", "update").awaitTermination(120)
        if i == 0:
            assert {(r.cnt, r.sum_v) for r in kept} == {(1, 100), (1, 200)}
        if i == 1:
            assert kept == []


def test_sliding_windows_and_sessions_end_as_batch(spark, parts, tmp_path):
    folder, ev, meta, z = parts
    for name, make in (("sliding", lambda p, delay: P.windowed(p, "2 days", "1 day", delay)), ("session", lambda p, delay: P.sessions(p, delay=delay))):
        want = make(P.zone_stream(P.event_pixels(ev, meta).withColumn("ts", F.col("ts").cast("timestamp")), z, meta), None)
        px = P.event_pixels(P.source(spark, folder, ev.schema, 10), meta)
        P.to_table(make(P.zone_stream(px, z, meta), "40 days"), f"st_{name}", f"{tmp_path}/{name}", "complete" if name == "sliding" else "append").awaitTermination(180)
        got = sorted(map(tuple, spark.table(f"st_{name}").collect()))
        if name == "sliding":
            assert got == sorted(map(tuple, want.collect()))
        else:  # sessions still open at the end of the input stay in state
            assert set(got) <= set(map(tuple, want.collect()))


def test_custom_state_with_time_to_live(spark, parts, tmp_path):
    folder, ev, meta, z = parts
    keys = {"spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider", "spark.sql.shuffle.partitions": "1"}
    old, got = {k: spark.conf.get(k) for k in keys}, {}
    try:
        for k, v in keys.items():
            spark.conf.set(k, v)
        px = P.event_pixels(P.source(spark, folder, ev.schema), meta)
        stream = P.stateful_stats(P.zone_stream(px, z, meta), 3_600_000)
        query = P.to_batches(stream, lambda df, _: got.update({r.zone_id: (r.cnt, r.sum_v, r.min_v, r.max_v) for r in df.collect()}), str(tmp_path))
        query.processAllAvailable()
        query.stop()  # with a time to live Spark goes on to look for state that ends
    finally:
        for k, v in old.items():
            spark.conf.set(k, v)
    raster = from_key(ev, "event_id", F.round(F.col("value") * 100).cast("long"), (32, 32))
    want = planner.zonal_stats(raster, z, method="merge_ordered", keep_empty=False)
    assert got == {r.zone_id: (r.cnt, r.sum_v, r.min_v, r.max_v) for r in want.collect()}
