"""Batch forms of the streaming operations, with SQL beside them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import oracle as O
from ..functions.grid import from_key
from ..sources.layers import table, zone_layer
from ..workloads import register
from . import pixels

_PAIR = f"{O.pairs('ZN', 'RE')}, p as (select zone_id, v, ts from pair join m on true join events on event_id = y * w + x)"


def _pairs(spark: SparkSession, d: str) -> DataFrame:
    ev = table(spark, d, "events")
    meta = from_key(ev, "event_id", F.lit(0), (32, 32)).meta
    return pixels.zone_stream(pixels.event_pixels(ev, meta), zone_layer(spark, d, "ZN", meta), meta)


@register("st_tumbling_batch", f"with {_PAIR} select zone_id, date_trunc('day', ts) as start, count(*) as cnt, cast(sum(v) as bigint) as sum_v from p group by 1, 2")
def st_tumbling_batch(spark: SparkSession, d: str) -> DataFrame:
    return _naive(pixels.windowed(_pairs(spark, d), delay=None), "start")


@register(
    "st_sliding_batch",
    f"with {_PAIR}, q as (select zone_id, v, date_trunc('day', ts) - to_days(cast(i as integer)) as start from p, (select unnest(range(2)) as i)) select zone_id, start, count(*) as cnt, cast(sum(v) as bigint) as sum_v from q group by 1, 2",
)
def st_sliding_batch(spark: SparkSession, d: str) -> DataFrame:
    return _naive(pixels.windowed(_pairs(spark, d), "2 days", "1 day", None), "start")


@register(
    "st_session_batch",
    f"""with {_PAIR}, f as (select zone_id, ts, case when ts - lag(ts) over w < interval 2 hours then 0 else 1 end as fresh from p window w as (partition by zone_id order by ts)),
s as (select zone_id, ts, sum(fresh) over (partition by zone_id order by ts rows between unbounded preceding and current row) as k from f)
select zone_id, min(ts) as start, max(ts) + interval 2 hours as finish, count(*) as cnt from s group by zone_id, k""",
)
def st_session_batch(spark: SparkSession, d: str) -> DataFrame:
    return _naive(pixels.sessions(_pairs(spark, d), delay=None), "start", "finish")


def _naive(df: DataFrame, *columns: str) -> DataFrame:
    """Times without a zone, as the tables have them."""
    for c in columns:
        df = df.withColumn(c, F.col(c).cast("timestamp_ntz"))
    return df
