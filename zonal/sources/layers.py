"""The study's raster and zone layers, built from the given tables by whole-number rules."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import grid
from ..functions.arith import floor_div, long
from ..functions.grid import GridMeta, RasterLayer
from ..operators import zones
from ..operators.zones import ZoneLayer, point

OUTER = [(-2, -5), (2, -5), (5, -2), (5, 2), (2, 5), (-2, 5), (-5, 2), (-5, -2)]
INNER = [(0, -2), (2, 0), (0, 2), (-2, 0)]
TEETH = 40


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cents(column: str):
    return F.round(F.col(column) * 100).cast("long")


def raster(spark: SparkSession, sf_dir: str, name: str) -> RasterLayer:
    t = lambda n: table(spark, sf_dir, n)
    if name == "RO":
        return grid.from_key(t("orders"), "o_orderkey", cents("o_totalprice"))
    if name == "RT":  # measurements that aren't whole numbers, in 64ths, so that any order adds up alike; some missing
        some = F.when(F.col("o_orderkey") % 11 != 0, F.round(F.col("o_totalprice") * 100) / F.lit(64.0))
        return grid.from_key(t("orders"), "o_orderkey", some)
    if name == "RC":
        return grid.from_key(t("orders"), "o_orderkey", F.substring("o_orderpriority", 1, 1).cast("long"))
    if name == "RE":
        return grid.from_key(t("events"), "event_id", cents("value"), (32, 32))
    if name == "RD":
        return grid.from_key(t("documents"), "doc_id", F.col("n_chars").cast("long"))
    if name == "RL":
        shape = grid.from_key(t("documents"), "doc_id", F.lit(0)).meta
        k = F.col("doc_id").cast("long")
        return RasterLayer(t("labels").select(F.pmod(k, long(shape.cols)).alias("x"), floor_div(k, shape.cols).alias("y"), F.col("quality").cast("long").alias("v")), shape)
    if name == "RM":
        return grid.from_matrix(t("embeddings"), "vec_id", "embedding", 1_000_000)
    if name == "RP":
        made = grid.from_cells(t("lineitem"), "l_partkey", "l_suppkey", F.col("l_quantity").cast("long"), (16, 1))
        return RasterLayer(made.df, made.meta.with_tiles(-(-made.meta.cols // 36), 1))
    raise ValueError(f"unknown raster {name!r}")


def _corner(meta: GridMeta, i, j):
    """Corner (i, j) of the 5 by 5 quadrilaterals; inner corners are shaken."""
    a = F.when((i == 0) | (i == 5), 0).otherwise(11 * (F.pmod(7 * i + 13 * j, long(5)) - 2))
    b = F.when((j == 0) | (j == 5), 0).otherwise(9 * (F.pmod(11 * i + 5 * j, long(5)) - 2))
    return point(floor_div(16 * meta.cols * i, 5) + a, floor_div(16 * meta.rows * j, 5) + b)


def zone_layer(spark: SparkSession, sf_dir: str, name: str, meta: GridMeta) -> ZoneLayer:
    t = lambda n: table(spark, sf_dir, n)
    w, h = meta.cols, meta.rows

    def scattered(df: DataFrame, key: str, templates, scale, fx: int, fy: int, dx: int, dy: int) -> ZoneLayer:
        k = F.col(key).cast("long")
        return zones.from_template(df, key, templates, scale, F.pmod(fx * k, long(w)) * 16 + dx, F.pmod(fy * k, long(h)) * 16 + dy)

    if name in ("ZN", "ZR"):
        k = F.col("n_nationkey").cast("long")
        i, j = F.pmod(k, long(5)), floor_div(k, 5)
        ring = F.array(_corner(meta, i, j), _corner(meta, i + 1, j), _corner(meta, i + 1, j + 1), _corner(meta, i, j + 1))
        layer = zones.from_rings(t("nation"), "n_nationkey", F.array(ring), "n_regionkey", "n_name")
        return layer if name == "ZN" else zones.dissolve(layer, "n_regionkey")
    if name == "ZS":
        return scattered(t("supplier"), "s_suppkey", [OUTER, INNER], 10 + F.pmod(F.col("s_suppkey").cast("long"), long(20)), 37, 61, 3, 5)
    if name == "ZC":
        return scattered(t("customer"), "c_custkey", [OUTER], 3 + F.pmod(F.col("c_custkey").cast("long"), long(9)), 7919, 104729, 3, 5)
    if name == "ZP":
        return scattered(t("part"), "p_partkey", [INNER], 2 + F.pmod(F.col("p_size").cast("long"), long(13)), 613, 769, 1, 1)
    if name == "ZB":
        r = F.col("r_regionkey").cast("long")
        base, tooth = floor_div(16 * h * r, 5) + 3, (3 * (16 * h // 5 - 6)) // 4
        comb = [point(7 + (16 * w - 14) * t_ // (2 * TEETH), base + (tooth if t_ % 2 else 0)) for t_ in range(2 * TEETH + 1)]
        top = floor_div(16 * h * (r + 1), 5) - 3
        ring = F.array(*comb, point(7 + 16 * w - 14, top), point(7, top))
        return zones.from_rings(t("region"), "r_regionkey", F.array(ring))
    raise ValueError(f"unknown zone layer {name!r}")


def layers(spark: SparkSession, sf_dir: str, zone: str, rast: str) -> tuple[RasterLayer, ZoneLayer]:
    r = raster(spark, sf_dir, rast)
    return r, zone_layer(spark, sf_dir, zone, r.meta)
