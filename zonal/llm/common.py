"""Shared pieces of the training-data operators: columns, shared storage, SQL bits."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Words are maximal runs of anything but space and the five ASCII line and tab characters.
WORD = r"[^\x20\x09-\x0D]+"

_LOCAL: dict[str, tempfile.TemporaryDirectory] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir`` of the session.

    Only where the session names none and all of Spark is one JVM, as in tests, a temporary
    folder stands in; elsewhere each executor would write to a disk of its own.
    """
    there = spark.conf.get("spark.checkpoint.dir", None)
    if there:
        return there.rstrip("/")
    master = spark.sparkContext.master
    if master.startswith("local-cluster") or not master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
    if "dir" not in _LOCAL:
        _LOCAL["dir"] = tempfile.TemporaryDirectory(prefix="zonal-shared-")
        atexit.register(_LOCAL["dir"].cleanup)
    return "file://" + _LOCAL["dir"].name


def shared_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex[:12]}"


def materialize(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` once to the shared folder and read it back, which cuts its lineage.

    A lost executor then costs a re-read of Parquet, not a recomputation.
    """
    path = shared_path(df.sparkSession, tag)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._kept_at = path
    return out


def discard(*tables: DataFrame) -> None:
    """Delete the files of materialized tables that nothing reads any more."""
    for table in tables:
        path = table.__dict__.pop("_kept_at", None)
        if path:
            context = table.sparkSession.sparkContext
            place = context._jvm.org.apache.hadoop.fs.Path(path)
            place.getFileSystem(context._jsc.hadoopConfiguration()).delete(place, True)


#: A key with more rows than the first number, and than the total by the second, is cut into pieces.
HOT_ROWS, HOT_KEYS = 500, 2000


def join_by_key(rows: DataFrame, table: DataFrame, keys: list[str], n_col: str, spread_by: list[str], how: str = "inner") -> DataFrame:
    """``rows`` joined with ``table`` so that no key's rows meet in one task.

    ``table`` is written, has one row a key and in ``n_col`` how many of ``rows`` have the key
    (or more). Keys above the threshold are at most ``HOT_KEYS`` many, since the threshold
    grows with the total: their list is broadcast, their rows are dealt over as many pieces as
    they fill by a hash of ``spread_by``, and their table row is copied to each piece.
    """
    most, total = table.agg(F.max(n_col), F.sum(n_col)).first()
    piece = max(HOT_ROWS, (total or 0) // HOT_KEYS)
    if (most or 0) <= piece:
        return rows.join(table, keys, how)
    pieces = F.ceil(F.col(n_col) / F.lit(piece)).cast("int")
    hot = table.where(F.col(n_col) > piece).select(*keys, pieces.alias("__pieces"))
    dealt = rows.join(F.broadcast(hot), keys, "left")
    dealt = dealt.withColumn("__piece", F.coalesce(F.pmod(F.xxhash64(*spread_by), F.col("__pieces")), F.lit(0)).cast("int")).drop("__pieces")
    copied = table.withColumn("__piece", F.explode(F.sequence(F.lit(0), F.greatest(pieces, F.lit(1)) - 1)))
    return dealt.join(copied, [*keys, "__piece"], how).drop("__piece")


#: Bytes of text whose hashes or n-grams one task holds at a time.
BUCKET_BYTES = 16 << 20


def buckets_for(texts: DataFrame, text_col: str, times: int = 1) -> int:
    """Buckets for work on all texts, so that a bucket's share is bounded whatever their size."""
    size = texts.agg(F.sum(F.octet_length(text_col))).first()[0] or 0
    return max(int(texts.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-times * size // BUCKET_BYTES))


def text_or_empty(name: str) -> Column:
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def word_count(text: Column) -> Column:
    return F.regexp_count(text, F.lit(WORD)).cast("long")


def documents(spark: SparkSession, sf_dir: str, table: str = "documents") -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def hash_unit(*parts: Column) -> Column:
    """A reproducible number in [0, 1) from the first 32 bits of an MD5 over the parts."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", *parts)), 1, 8), 16, 10).cast("long") / F.lit(4294967296.0)
