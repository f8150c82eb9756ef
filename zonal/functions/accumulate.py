"""Accumulators: native aggregates where they exist, user code otherwise.

Partials are columns that merge by native aggregates, so Spark runs them before and after
the exchange on zone_id, and pairs of (zone, value) are never stored.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from typing import Any, Protocol

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: name: (partial per run from a list of values, merge of partials); counts skip nodata.
DEFAULT = ("min", "max", "sum", "count")


def is_whole(kind: T.DataType) -> bool:
    return isinstance(kind, T.IntegralType)


def sum_type(kind: T.DataType, wide: bool = False) -> str:
    """The type that measurements of a type add up in: whole numbers and decimals exactly."""
    if isinstance(kind, T.DecimalType):
        return f"decimal(38,{kind.scale})"
    if is_whole(kind):
        return "decimal(38,0)" if wide else "bigint"
    if isinstance(kind, T.FractionalType):
        return "double"
    raise ValueError(f"measurements must be numbers, not {kind.simpleString()}")


def value_aggs(aggs: tuple[str, ...] = DEFAULT, of: DataFrame | None = None, v: str = "v", wide: bool = False) -> list[Column]:
    """Aggregates over the (zone, value) pairs ``of``, whose values are long unless given.

    ``wide``: sums of whole numbers in 38 digits, for 100 TB. Nulls are nodata: no aggregate
    sees them.
    """
    kind = of.schema[v].dataType if of is not None else T.LongType()
    whole = is_whole(kind)
    if not whole and "bit_or" in aggs:
        raise ValueError("bit_or needs whole numbers")
    c = F.col(v)
    exact = c.cast(sum_type(kind, wide))
    n = F.count(c)
    made = {
        "count": lambda: n.cast("long").alias("cnt"),
        "sum": lambda: F.sum(exact).cast(sum_type(kind, wide)).alias("sum_v"),
        "min": lambda: F.min(c).alias("min_v"),
        "max": lambda: F.max(c).alias("max_v"),
        "avg": lambda: (F.sum(exact) / n).alias("avg_v"),
        "var": lambda: F.var_pop(c).alias("var_v") if not whole else ((F.sum(exact.cast("decimal(38,0)") * exact) - F.sum(exact.cast("decimal(38,0)")) * F.sum(exact) / n) / n).cast("double").alias("var_v"),
        "stddev": lambda: F.stddev_pop(c).alias("stddev_v"),
        "bit_or": lambda: F.bit_or(c).alias("bits_v"),
        "any": lambda: F.bool_or(c != 0).alias("any_v"),
        "all": lambda: F.bool_and(c != 0).alias("all_v"),
        "approx_median": lambda: F.percentile_approx(c, 0.5).alias("median_v"),
        "approx_distinct": lambda: F.approx_count_distinct(c).alias("distinct_v"),
        "mode": lambda: F.mode(c).alias("mode_v"),
        "kll": lambda: F.call_function("kll_sketch_agg_bigint" if whole else "kll_sketch_agg_double", c.cast("long" if whole else "double")).alias("kll_v"),
        "hll": lambda: F.hll_sketch_agg(c if whole else c.cast("string")).alias("hll_v"),
    }
    return [made[a]() for a in aggs]


#: Partials a run carries when it is reduced at once, and how they merge.
RUN_PARTIALS = {"count": ("cnt", F.sum), "sum": ("sum_v", F.sum), "min": ("min_v", F.min), "max": ("max_v", F.max)}


def merge_partials(df: DataFrame, by: list[str], aggs: tuple[str, ...] = DEFAULT, wide: bool = False) -> DataFrame:
    """Final aggregates from run or chunk partials cnt, sum_v, min_v, max_v."""
    need = set(aggs) | ({"sum", "count"} if "avg" in aggs else set())
    of = {"cnt": "bigint"} | ({"sum_v": sum_type(df.schema["sum_v"].dataType, wide)} if "sum" in need else {})
    out = [f(F.col(c).cast(of[c]) if f is F.sum else F.col(c)).alias(c) for a, (c, f) in RUN_PARTIALS.items() if a in need]
    got = df.groupBy(*by).agg(*out)
    if "sum" in need:
        got = got.withColumn("sum_v", F.col("sum_v").cast(of["sum_v"]))
    if "count" in need:
        got = got.withColumn("cnt", F.col("cnt").cast("long"))
    if "avg" in aggs:
        got = got.withColumn("avg_v", F.col("sum_v") / F.nullif("cnt", F.lit(0)))
    names = {"count": "cnt", "sum": "sum_v", "min": "min_v", "max": "max_v", "avg": "avg_v"}
    return got.select(*by, *[names[a] for a in aggs])


def histogram(pairs: DataFrame, bins: tuple[float, float, int] | None = None, as_map: bool = False) -> DataFrame:
    """zone_id, class, cnt of (zone_id, v) pairs; equal-width bins if asked for, which values
    that aren't whole numbers need."""
    if bins is None and not is_whole(pairs.schema["v"].dataType):
        raise ValueError("a histogram of values that aren't whole numbers needs bins")
    c = F.col("v") if bins is None else F.width_bucket("v", F.lit(float(bins[0])), F.lit(float(bins[1])), F.lit(bins[2]))
    out = pairs.where("v is not null").groupBy("zone_id", c.cast("long").alias("class")).agg(F.count(F.lit(1)).alias("cnt"))
    if not as_map:
        return out
    entries = F.sort_array(F.collect_list(F.struct("class", "cnt")))
    return out.groupBy("zone_id").agg(F.map_from_entries(entries).alias("histogram"))


class Accumulator(Protocol):
    """Any associative and commutative fold. States must pickle; ``columns`` names the result."""

    columns: str

    def init(self) -> Any: ...

    def update_many(self, state: Any, values: np.ndarray) -> Any: ...

    def merge(self, a: Any, b: Any) -> Any: ...

    def finish(self, state: Any) -> tuple: ...


def accumulate_custom(pairs: DataFrame, acc: Accumulator) -> DataFrame:
    """zone_id and the accumulator's columns, from (zone_id, v) pairs.

    States are built inside the task that makes the pairs; one row a zone and batch crosses
    the exchange.
    """

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        states: dict[int, Any] = {}
        for b in batches:
            zones, values = b.column(0).to_numpy(zero_copy_only=False), b.column(1).to_numpy(zero_copy_only=False)
            order = np.argsort(zones, kind="stable")
            z = zones[order]
            cuts = np.flatnonzero(np.concatenate([[True], z[1:] != z[:-1], [True]])) if len(z) else [0]
            for s, e in zip(cuts[:-1], cuts[1:], strict=True):
                key = int(z[s])
                states[key] = acc.update_many(states.get(key, acc.init()), values[order[s:e]])
            if len(states) > 100_000:
                yield pa.RecordBatch.from_arrays([pa.array(list(states)), pa.array([pickle.dumps(x) for x in states.values()], pa.binary())], ["zone_id", "state"])
                states = {}
        yield pa.RecordBatch.from_arrays([pa.array(list(states), pa.int64()), pa.array([pickle.dumps(x) for x in states.values()], pa.binary())], ["zone_id", "state"])

    def final(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, state, out = None, None, []
        for b in batches:
            for key, raw in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                if key != now:
                    if now is not None:
                        out.append((now, *acc.finish(state)))
                    now, state = key, pickle.loads(raw)
                else:
                    state = acc.merge(state, pickle.loads(raw))
        if now is not None:
            out.append((now, *acc.finish(state)))
        names = ["zone_id", *[c.split()[0] for c in acc.columns.split(", ")]]
        yield pa.RecordBatch.from_pylist([dict(zip(names, r, strict=True)) for r in out], schema=to_arrow)

    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    ddl = f"zone_id bigint, {acc.columns}"
    to_arrow = to_arrow_schema(_parse_datatype_string(ddl))
    states = pairs.select(F.col("zone_id").cast("long"), "v").where("v is not null").mapInArrow(partial, "zone_id bigint, state binary")
    return states.repartition("zone_id").sortWithinPartitions("zone_id").mapInArrow(final, ddl)


def keep_empty(result: DataFrame, zones: DataFrame, attributes: tuple[str, ...] = ()) -> DataFrame:
    """One row per zone: zones without a pixel get count 0 and nulls."""
    out = zones.select(F.col("zone_id"), *attributes).join(result, "zone_id", "left")
    return out.withColumn("cnt", F.coalesce("cnt", F.lit(0).cast("long"))) if "cnt" in result.columns else out
