"""Mixing sources to target weights by deterministic repetition.

Tokens are summed per source, weights become targets by filling up (no target above
``cap`` times the source's size, the excess reshared by weight), and a source's repetition
rate is target / size. A document is emitted floor(rate) times plus one Bernoulli copy with
probability frac(rate). The Bernoulli draws are hash-seeded and stratified: inside bins of
about ``bin_docs`` documents of a source, in order of size, document k gets the copy when
floor(k f + u) steps up, u being the hash of (seed, source, bin). Each single draw has
probability f exactly, neighbours exclude each other, so a source's total stays within
about one document a bin of its target (independent draws miss three to five times as much),
and reruns agree. No draw needs other sources' rows,
and no task holds more than a bin.

The filling-up works on the table of sources, one row each, by running sums in order of
cap / weight: sources are capped as long as the water level of the rest lies above them; from
the first one that isn't capped on, levels only fall, so the largest open one is the level.

Defined results: null text has size 0; null is a source of its own, last in order; a source
of size 0 has target 0 and takes nothing; empty tables give empty results; repeated rows are
documents of their own.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import hash_unit, materialize, text_or_empty, word_count

#: A table of sources up to this many rows is broadcast; its rows are counted first.
BROADCAST_SOURCES = 100_000


def document_sizes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    return docs.select(
        F.col(id_col).alias("doc_id"), F.col(source_col).cast("string").alias("source"), word_count(text_or_empty(text_col)).alias("size")
    )


def source_targets(sizes: DataFrame, weights: Sequence[int] = (5, 2, 1), share: float = 1.5, cap: int = 2) -> DataFrame:
    """source, n_docs, source_size, weight, target. ``sizes`` has source and size."""
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("n_docs"))
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    place = F.row_number().over(by_name)
    weight = F.element_at(F.array(*[F.lit(int(w)) for w in weights]), (F.pmod(place - 1, F.lit(len(weights))) + 1).cast("int"))
    per = per.withColumn("place", place).withColumn("weight", weight.cast("long")).withColumn("most", F.col("source_size") * cap)
    filling = Window.orderBy(F.col("most") / F.col("weight"), "place")
    before = filling.rowsBetween(Window.unboundedPreceding, -1)
    every = Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    wanted = F.sum("source_size").over(every) * F.lit(float(share))
    left = wanted - F.coalesce(F.sum("most").over(before), F.lit(0))
    open_weight = F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(before), F.lit(0))
    per = per.withColumn("level", left / open_weight)
    per = per.withColumn("open", F.col("level") * F.col("weight") <= F.col("most"))
    per = per.withColumn("final", F.max(F.when(F.col("open"), F.col("level"))).over(every))
    target = F.least(F.col("most").cast("double"), F.coalesce(F.col("final") * F.col("weight"), F.col("most").cast("double")))
    return per.select("source", "n_docs", "source_size", "weight", target.alias("target"))


def mix(
    docs: DataFrame,
    weights: Sequence[int] = (5, 2, 1),
    share: float = 1.5,
    cap: int = 2,
    seed: int = 17,
    bin_docs: int = 1000,
    id_col: str = "doc_id",
    text_col: str = "text",
    source_col: str = "source",
) -> DataFrame:
    """One row per document: doc_id, source, size, source_size, target, copies, taken."""
    sizes = materialize(document_sizes(docs, id_col, text_col, source_col), "mix-sizes")
    targets = materialize(source_targets(sizes, weights, share, cap), "mix-targets")
    targets = targets.withColumnRenamed("source", "of")
    if targets.count() <= BROADCAST_SOURCES:
        targets = F.broadcast(targets)
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    rows = sizes.join(targets, F.col("source").eqNullSafe(F.col("of"))).select(
        "doc_id", "source", "size", "source_size", "target", rate.alias("rate"),
        F.ceil(F.col("n_docs") / F.lit(bin_docs)).cast("long").alias("bins"),
        hash_unit(F.lit(str(seed)), F.col("doc_id").cast("string")).alias("u"),
    )
    rows = rows.withColumn("bin", F.floor(F.col("u") * F.col("bins")).cast("long"))
    order = Window.partitionBy("source", "bin").orderBy(F.col("size").desc(), "u", "doc_id")
    rows = rows.withColumn("k", F.row_number().over(order).cast("long"))
    start = hash_unit(F.lit(str(seed)), F.coalesce(F.concat(F.lit("s"), F.col("source")), F.lit("null")), F.col("bin").cast("string"))
    f = F.col("rate") - F.floor("rate")
    extra = F.floor(F.col("k") * f + start) - F.floor((F.col("k") - 1) * f + start)
    copies = (F.floor("rate") + extra).cast("long")
    return rows.select("doc_id", "source", "size", "source_size", "target", copies.alias("copies"), (F.col("size") * copies).alias("taken"))


def emit(docs: DataFrame, mixed: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """The mixed corpus: each document's row as often as it is taken, with its own columns.

    Rows with equal ids are told apart by source and size; those that agree in all three share
    their copies evenly, so that the corpus holds exactly what ``mixed`` takes.
    """
    keys = ["__id", "__source", "__size"]
    taken = mixed.select(F.col("doc_id").alias("__id"), F.col("source").alias("__source"), F.col("size").alias("__size"), "copies")
    taken = taken.groupBy(*keys).agg(F.sum("copies").alias("__copies"), F.count(F.lit(1)).alias("__rows"))
    taken = materialize(taken.where("__copies > 0"), "mix-taken")
    rows = docs.withColumn("__of", F.struct(F.col(id_col).alias("i"), F.col("source").cast("string").alias("s"), word_count(text_or_empty("text")).alias("n")))
    same = F.col("__of.i").eqNullSafe(F.col("__id")) & F.col("__of.s").eqNullSafe(F.col("__source")) & (F.col("__of.n") == F.col("__size"))
    met = rows.join(taken, same)
    if taken.where("__rows > 1").isEmpty():
        met = met.withColumn("__share", F.col("__copies"))
    else:
        place = F.row_number().over(Window.partitionBy("__of").orderBy(F.lit(1)))
        met = met.withColumn("__share", F.floor(F.col("__copies") / F.col("__rows")) + (place <= F.col("__copies") % F.col("__rows")).cast("int")).where("__share > 0")
    return met.withColumn("__k", F.explode(F.sequence(F.lit(1), F.col("__share").cast("int")))).select(*docs.columns)
