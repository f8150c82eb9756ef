"""A training-data pipeline over ``documents``: five stages, each an operator of zonal.llm.

Every stage takes (spark, docs, sf_dir) and works on all rows of ``docs``; its result is
written as Parquet and read again as the next stage's docs. All but the last return the
columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from zonal.llm import line_dedup, mixing, packing, quality, similar
from zonal.llm.common import discard, documents, materialize
from zonal.llm.queries import LINE_PAGES
from zonal.workers import let_workers_import

#: A line of so many words is boilerplate on more than this share of its source's documents.
#: Planted boilerplate is on about 8.5 to 13.5 % of a source's documents; short lines of clean text,
#: which reach 5 %, are told from it by their length.
SOURCE_RATIO, LINE_WORDS = 0.02, 8


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go."""
    let_workers_import(spark)
    return quality.keep_good(docs, quality.fit(docs, documents(spark, sf_dir, "labels")))


def line_dedup_by_source(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that are boilerplate of their source go; n_chars follows the text."""
    host = F.coalesce(F.col("source"), F.lit(""))
    out = line_dedup.drop_boilerplate(docs, host, "doc_id", "text", SOURCE_RATIO, LINE_PAGES, min_words=LINE_WORDS)
    return out.withColumn("n_chars", F.when(F.col("__n_dropped") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))).select(*docs.columns)


def simhash_near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of every group of texts alike to 0.8 in five-word shingles the smallest id stays."""
    let_workers_import(spark)
    found = similar.similar_groups(docs)
    gone = found.where("doc_id <> component_id").select(F.col("doc_id").alias("__gone"))
    return docs.join(gone, F.col("doc_id") == F.col("__gone"), "left_anti").select(*docs.columns)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources come near their target weights; documents appear as often as they are taken."""
    return mixing.emit(docs, mixing.mix(docs)).select(*docs.columns)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token sequences of at most 2048 ids."""
    let_workers_import(spark)
    return packing.pack(docs)


STAGES = [
    ("quality_classifier", quality_classifier),
    ("line_dedup", line_dedup_by_source),
    ("simhash_near_dedup", simhash_near_dedup),
    ("mix_sources", mix_sources),
    ("packing", pack_sequences),
]

#: Learned scores, fingerprint links and token ids are beyond SQL; tests use brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, stage in STAGES[:-1]:
        before, docs = docs, materialize(stage(spark, docs, sf_dir), name)
        discard(before)
    return STAGES[-1][1](spark, docs, sf_dir)
