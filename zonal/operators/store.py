"""The crossing store: sorted runs in Parquet with a footer, in place of sorted triples.

A chunk is a directory of files by ranges of tiles, each sorted by tile, row, zone and column,
so row-group statistics and the page index lead a reader to a tile; the footer says which
tiles and zones a chunk has and where each tile's first entry lies. Tile ids follow from
coordinates, so they need not be stored. Runs are made once: the footer is counted from the
written files.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.grid import GridMeta, tile_id
from .runs import merge_order


def footer(runs: DataFrame) -> DataFrame:
    """chunk_id, tile_id, first_row, n_runs, zone_ids; ``runs`` are cut at tiles."""
    per = runs.groupBy("chunk_id", "tile_id").agg(F.count(F.lit(1)).alias("n_runs"), F.sort_array(F.collect_set("zone_id")).alias("zone_ids"))
    before = Window.partitionBy("chunk_id").orderBy("tile_id").rowsBetween(Window.unboundedPreceding, -1)
    return per.select("chunk_id", "tile_id", F.coalesce(F.sum("n_runs").over(before), F.lit(0)).cast("long").alias("first_row"), "n_runs", "zone_ids")


def write(runs: DataFrame, path: str, codec: str = "snappy", drop_tile_id: bool = False, plain: bool = False, meta: GridMeta | None = None) -> None:
    """Runs to ``path``/runs and the footer to ``path``/footer. ``plain`` turns dictionaries
    off, for measuring what a codec alone saves; without tile ids the footer needs ``meta``, or
    else runs are made once more."""
    ordered = merge_order(runs, meta)
    if drop_tile_id:
        ordered = ordered.drop("tile_id")
    writer = ordered.write.partitionBy("chunk_id").option("compression", codec)
    if plain:
        writer = writer.option("parquet.enable.dictionary", "false")
    writer.parquet(f"{path}/runs")
    written = runs if drop_tile_id and meta is None else read(runs.sparkSession, path, meta, schema=ordered.schema)
    footer(written).write.parquet(f"{path}/footer")


def read(spark: SparkSession, path: str, meta: GridMeta | None = None, chunks: list[int] | None = None, schema=None) -> DataFrame:
    """The runs, or those of some chunks: other chunks' directories aren't read."""
    df = (spark.read.schema(schema) if schema else spark.read).parquet(f"{path}/runs")
    if chunks is not None:
        df = df.where(F.col("chunk_id").isin(chunks))
    return df if "tile_id" in df.columns else df.withColumn("tile_id", tile_id(meta, F.col("x0"), F.col("y")))


def read_footer(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(f"{path}/footer")


def stored_bytes(spark: SparkSession, path: str) -> int:
    """Bytes of the files under a path, on any file system that Spark knows."""
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    return hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(hadoop).getLength()
