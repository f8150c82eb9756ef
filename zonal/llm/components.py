"""Connected components of a table of links, by alternating stars.

Every round points nodes at the smallest node they know of, first from the side of larger
neighbours, then of smaller ones; the number of rounds grows with the logarithm of a
component's size. Tasks first replace their own links by a spanning forest, so groups whose
links lie together cost no rounds. Rounds are written to the shared folder, never kept in
executors only; a round's tables are deleted when the next stands, a node with a great many
links is dealt over many tasks, and nothing but a few counts reaches the driver.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, join_by_key, materialize


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, smallest node of its component within these links), without the roots' own rows."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    label = np.arange(len(nodes))
    while True:  # hook larger roots to smaller, then halve paths until flat
        lx, ly = label[x], label[y]
        open_ = lx != ly
        if not open_.any():
            break
        x, y, lx, ly = x[open_], y[open_], lx[open_], ly[open_]
        np.minimum.at(label, np.maximum(lx, ly), np.minimum(lx, ly))
        while True:
            up = label[label]
            if np.array_equal(up, label):
                break
            label = up
    own = label != np.arange(len(nodes))
    return nodes[own], nodes[label[own]]


def _local_forest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    a = b = np.empty(0, np.int64)
    for batch in batches:
        a, b = forest(np.concatenate([a, batch.column(0).to_numpy(zero_copy_only=False)]), np.concatenate([b, batch.column(1).to_numpy(zero_copy_only=False)]))
        if len(a) > 2_000_000:
            yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["a", "b"])
            a = b = np.empty(0, np.int64)
    yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["a", "b"])


def connected_components(links: DataFrame) -> DataFrame:
    """``links`` has two long columns; returns (node, root) for all nodes but the roots."""
    a, b = links.columns
    links = materialize(links.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b")).where("a <> b"), "links")
    edges = materialize(links.mapInArrow(_local_forest, "a bigint, b bigint"), "links")  # no two Python workers at once a task
    discard(links)
    while not edges.isEmpty():
        both = edges.select(F.col("a").alias("u"), F.col("b").alias("v")).union(edges.select(F.col("b").alias("u"), F.col("a").alias("v")))
        least = materialize(both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"), F.count(F.lit(1)).alias("n")), "links-least")
        larger = join_by_key(both.where("v > u"), least, ["u"], "n", ["v"]).select(F.col("v").alias("u"), F.col("m").alias("v"))
        down = materialize(larger.where("u <> v").distinct(), "links")  # each row: a node and a smaller one
        below = materialize(down.groupBy("u").agg(F.min("v").alias("m"), F.count(F.lit(1)).alias("n")), "links-least")
        smaller = join_by_key(down, below, ["u"], "n", ["v"]).select(F.col("v").alias("a"), F.col("m").alias("b")).where("a <> b")
        after = materialize(below.select(F.col("u").alias("a"), F.col("m").alias("b")).union(smaller).distinct(), "links")
        discard(edges, least, down, below)
        edges = after
        # a forest of depth one is done: no root is a node of another tree
        roots = after.select(F.col("b").alias("a")).distinct()
        if roots.join(after, "a", "left_semi").isEmpty() and after.groupBy("a").count().where("count > 1").isEmpty():
            break
    return edges.select(F.col("a").alias("node"), F.col("b").alias("root"))
