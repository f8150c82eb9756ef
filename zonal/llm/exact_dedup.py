"""Exact duplicates: group by a 128-bit content hash, compare bytes inside the groups.

The grouping key of the aggregation is (hash, text): the hash spreads rows and orders the
compare, the text in the key makes the comparison of bytes part of the grouping, so texts
that merely share a hash never meet. The aggregation is partial before its exchange: a text
that a third of all rows share travels once per input split. The groups then shrink to
digests, and rows are told their group by (hash, SHA-256), a join of narrow rows in which a
huge group is dealt over many tasks; should two different texts ever agree on both, the
query stops with an error rather than merge them.

Defined results: a null text counts as empty; empty texts equal each other; a null id never
wins against another id; rows repeated with id and text are all marked alike; an empty table
gives an empty result; columns besides id and text are ignored.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import join_by_key, materialize, text_or_empty


def content_hash(text: Column) -> Column:
    return F.unhex(F.md5(text))


def exact_groups(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    keep: str = "smallest",
    hasher: Callable[[Column], Column] = content_hash,
) -> DataFrame:
    """One row per input row: doc_id, keep_id, group_size, kept, text_sha256."""
    if keep not in ("smallest", "largest"):
        raise ValueError(f"keep must be 'smallest' or 'largest', not {keep!r}")
    pick = F.min if keep == "smallest" else F.max
    rows = docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("text"))
    by_bytes = (
        rows.withColumn("h", hasher(F.col("text")))
        .groupBy("h", "text")
        .agg(pick("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
    )
    groups = materialize(
        by_bytes.select("h", F.sha2("text", 256).alias("sha"), "keep_id", "group_size")
        .groupBy("h", "sha")
        .agg(F.count(F.lit(1)).alias("texts"), F.first("keep_id").alias("keep_id"), F.first("group_size").alias("group_size"))
        .select(
            "h", "sha", "keep_id",
            F.when(F.col("texts") == 1, F.col("group_size"))
            .otherwise(F.raise_error(F.lit("two texts agree on both digests")).cast("long")).alias("group_size"),
        ),
        "exact-groups",
    )
    ids = rows.select("doc_id", hasher(F.col("text")).alias("h"), F.sha2("text", 256).alias("sha"))
    return join_by_key(ids, groups, ["h", "sha"], "group_size", ["doc_id"]).select(
        "doc_id", "keep_id", "group_size",
        F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"),
        F.col("sha").alias("text_sha256"),
    )


def drop_exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "smallest") -> DataFrame:
    """The rows that stay, with all their columns."""
    kept = exact_groups(docs, id_col, text_col, keep).where("kept").select(F.col("doc_id").alias("__kept_id")).distinct()
    return docs.join(kept, F.col(id_col).eqNullSafe(F.col("__kept_id")), "left_semi")
