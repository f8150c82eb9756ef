"""Approximate nearest neighbours by collision counting on single projections.

Vectors are projected on ``projections`` random lines; a block of rows keeps, for each line,
its projections as a sorted array. A query opens a window around its own projection on every
line; virtual rehashing widens all windows by the factor ``widen`` a round. A vector whose
projections lie in the windows of at least a threshold of the lines is a candidate; only
candidates are verified, that is, their exact measure is computed. The threshold follows from
the window's ``width`` in radii: a vector at the radius falls into each window with a known
probability, and reaches the threshold but for ``misses`` standard deviations. A query stops
when its ``k``-th best verified distance is at most ``slack`` times the radius that the windows
stand for, or when every row of the block is a candidate. The first radius is the typical
distance of a k-th neighbour on a sample of the block, so most queries need few rounds. A
query that finds fewer than k rows then goes on at a radius where some of a sample collide.

Collisions are counted over the rows inside the windows or, where these are fewer, outside.

Nearness by inner product becomes nearness by distance with one more coordinate: data rows
get sqrt(M^2 - |x|^2), queries 0, M being the largest norm; the order of distances is then
the reverse order of inner products.

Queries are written to the shared folder in files of ``query_block`` vectors. One pass over the
table answers all: a task indexes its rows block by block and reads the files of queries in
turn, so neither driver nor executors hold more than one block of each. Inside a file so few
queries are searched at a time that their candidates stay within ``CANDIDATES``. Per query and
block only k rows leave a task.

Defined results: vectors that are null, all zero, of another length than ``dim`` (default:
the most frequent one) or that hold null or non-finite components take no part; ties go to
smaller ids; a row is no candidate of a query with its own id; of query rows with equal ids
the one with the smallest vector asks; rows repeated under an id are candidates each; fewer
candidates than k give all of them; no queries or no rows give an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import ceil, erf, sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize

BLOCK_ROWS = 50_000
#: Candidates that the queries searched together may have at most, all of them together.
CANDIDATES = 1_000_000


def needed(projections: int, width: float, misses: float) -> int:
    """Lines on which a vector at the radius collides, but for so many standard deviations."""
    p = erf(width / 2 / sqrt(2))
    return max(1, ceil(projections * p - misses * sqrt(projections * p * (1 - p))))


class BlockIndex:
    """Sorted projections of a block of rows."""

    def __init__(self, vectors: np.ndarray, lines: np.ndarray, top_norm: float):
        rest = np.sqrt(np.maximum(top_norm**2 - np.einsum("ij,ij->i", vectors, vectors), 0))
        self.values = lines[:, :-1] @ vectors.T
        self.order = np.empty(self.values.shape, np.int32)
        mixed = np.random.default_rng(len(vectors)).permutation(len(vectors))  # steps would meet copies at equal steps
        some: list[np.ndarray] = []
        for line, at, order in zip(lines[:, -1], self.values, self.order, strict=True):  # a line at a time: no second copy of the block
            at += rest * line
            some.append(at[mixed[:500]])
            order[:] = np.argsort(at, kind="stable")
            at[:] = at[order]
        self.some, self.sample = np.stack(some), vectors[mixed[:4000]]
        self.vectors, self.square, self.top = vectors, top_norm**2, top_norm

    def radius(self, queries: np.ndarray, k: int) -> float:
        """About the distance of a query's k-th neighbour, seen on a sample of both."""
        probe, some = queries[:: max(1, len(queries) // 64)][:64], self.sample
        d2 = (probe**2).sum(1)[:, None] + self.square - 2 * probe @ some.T
        place = min(1 + k * len(some) // len(self.vectors), len(some) - 1)
        return max(float(np.sqrt(np.maximum(np.partition(d2, place, axis=1)[:, place], 0)).mean()), 1e-9 * max(self.top, 1e-300))

    def sparse(self, at: np.ndarray, need: int) -> float:
        """About the half width up to which hardly a row collides with a query: a few of a sample do."""
        reach = np.partition(np.abs(self.some - at[:, None]), need - 1, axis=0)[need - 1]
        return float(np.partition(reach, min(4, len(reach) - 1))[min(4, len(reach) - 1)])

    def windows(self, at: np.ndarray, half: float | np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """First and last places, per query and line, of rows within ``half`` of the query."""
        lo = np.stack([np.searchsorted(v, a - half, "left") for v, a in zip(self.values, at.T, strict=True)], axis=1)
        hi = np.stack([np.searchsorted(v, a + half, "right") for v, a in zip(self.values, at.T, strict=True)], axis=1)
        return lo, hi

    def collisions(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        """For every row the lines on which it lies in the window."""
        m, n = self.order.shape
        inside = 2 * int((hi - lo).sum()) <= m * n
        cuts = zip(self.order, lo.tolist(), hi.tolist(), strict=True)
        parts = [o[a:b] for o, a, b in cuts] if inside else [x for o, a, b in cuts for x in (o[:a], o[b:])]
        counted = np.bincount(np.concatenate(parts), minlength=n)
        return counted if inside else m - counted

    def widened(self, counted: np.ndarray, lo: np.ndarray, hi: np.ndarray, new_lo: np.ndarray, new_hi: np.ndarray) -> np.ndarray:
        """``collisions`` of wider windows: only rows that they gain are counted."""
        cuts = zip(self.order, new_lo.tolist(), lo.tolist(), hi.tolist(), new_hi.tolist(), strict=True)
        parts = [x for o, a, b, c, d in cuts for x in (o[a:b], o[c:d])]
        return counted + np.bincount(np.concatenate(parts), minlength=len(counted))

    def search(self, queries: np.ndarray, at: np.ndarray, own: list[np.ndarray], k: int, need: int, radius: float, widen: float, slack: float, width: float) -> list[tuple[np.ndarray, np.ndarray]]:
        """For each query its candidates' places and scores: the rows that were verified."""
        n = len(self.vectors)
        far = np.einsum("ij,ij->i", queries, queries) + self.square
        places = [np.empty(0, np.int64)] * len(queries)
        scores = [np.empty(0)] * len(queries)
        open_, radii = np.arange(len(queries)), np.full(len(queries), radius)
        seen: list[tuple | None] = [None] * len(queries)
        while len(open_):
            los, his = self.windows(at[open_], width * radii[open_] / 2)
            still = []
            for i, q in enumerate(open_.tolist()):
                counted = self.collisions(los[i], his[i]) if seen[q] is None else self.widened(*seen[q], los[i], his[i])
                found = counted >= need
                found[own[q]] = False
                found[places[q]] = False
                new = np.flatnonzero(found)
                places[q] = np.concatenate([places[q], new])
                scores[q] = np.concatenate([scores[q], np.einsum("ij,j->i", self.vectors[new], queries[q])])
                done = len(places[q]) >= n - len(own[q])
                if not done and len(places[q]) >= k:
                    kth = -np.partition(-scores[q], k - 1)[k - 1]
                    done = sqrt(max(far[q] - 2 * kth, 0)) <= slack * radii[q]
                first, radii[q] = seen[q] is None, radii[q] * widen
                if not done and first and len(places[q]) < k:  # a block of copies has typical distances near 0
                    radii[q] = max(radii[q], 2 * self.sparse(at[q], need) / width)
                seen[q] = None if done else (counted.astype(np.int16), los[i], his[i])
                if not done:
                    still.append(i)
            open_ = open_[still]
        return list(zip(places, scores, strict=True))

    def best(self, queries: np.ndarray, at: np.ndarray, own: list[np.ndarray], ids: np.ndarray, k: int, *how) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """For each query the ids and scores of its k best candidates, ties to smaller ids.

        ``search`` holds a query's candidates until it stops, often a large share of the block:
        it is given as many queries as have ``CANDIDATES`` if every row is one."""
        step = max(1, CANDIDATES // len(self.vectors))
        for a in range(0, len(queries), step):
            for places, scores in self.search(queries[a : a + step], at[a : a + step], own[a : a + step], k, *how):
                best = np.lexsort((ids[places], -scores))[:k]
                yield ids[places[best]], scores[best]


def usable(vector: Column, dim: int) -> Column:
    finite = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    return vector.isNotNull() & (F.size(vector) == dim) & finite & F.exists(vector, lambda x: x != 0)


def nearest(
    table: DataFrame,
    is_query: Column,
    k: int = 20,
    projections: int = 96,
    width: float = 3.0,
    misses: float = 1.7,
    widen: float = 1.03,
    slack: float = 1.0,
    query_block: int = 20_000,
    seed: int = 11,
    id_col: str = "vec_id",
    vector_col: str = "embedding",
    dim: int | None = None,
) -> DataFrame:
    """query_id, rank, vec_id, score: the k largest inner products found for each query row."""
    rows = table.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).cast("array<double>").alias("v"), is_query.alias("q")).where("vec_id is not null")
    if dim is None:
        most = rows.where("v is not null").groupBy(F.size("v").alias("n")).count().orderBy(F.desc("count"), "n").first()
        dim = most["n"] if most else 0
    rows = rows.where(usable(F.col("v"), dim))
    norm = F.sqrt(F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x))
    size = rows.agg(F.max(norm).alias("top"), F.sum(F.col("q").cast("long")).alias("n")).first()
    top, n_queries = float(size["top"] or 1.0), int(size["n"] or 0)
    asked = rows.where("q").groupBy("vec_id").agg(F.min("v").alias("v"))
    asked = materialize(asked.repartition(max(1, -(-n_queries // query_block)), "vec_id"), "nearest-queries")
    where, need = asked._kept_at, needed(projections, width, misses)

    def files() -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Ids and vectors of the queries, a file at a time."""
        import pyarrow.parquet as pq
        from pyarrow import fs

        store, root = fs.FileSystem.from_uri(where) if ":" in where else (fs.LocalFileSystem(), where)
        for info in sorted(store.get_file_info(fs.FileSelector(root)), key=lambda f: f.path):
            if info.base_name.endswith(".parquet"):
                got = pq.ParquetFile(store.open_input_file(info.path)).read(["vec_id", "v"])
                if got.num_rows:
                    yield got.column("vec_id").to_numpy(), np.array(got.column("v").combine_chunks().flatten()).reshape(-1, dim)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lines = np.random.default_rng(seed).standard_normal((projections, dim + 1))

        def answer(vec_ids: np.ndarray, data: np.ndarray) -> Iterator[pa.RecordBatch]:
            index, by_id = BlockIndex(data, lines, top), np.argsort(vec_ids, kind="stable")
            for qids, queries in files():
                lo, hi = (np.searchsorted(vec_ids[by_id], qids, side) for side in ("left", "right"))
                own = [by_id[a:b] for a, b in zip(lo.tolist(), hi.tolist(), strict=True)]
                found = index.best(queries, queries @ lines[:, :-1].T, own, vec_ids, k, need, index.radius(queries, k), widen, slack, width)
                out = [(np.full(len(best), q), best, scores) for q, (best, scores) in zip(qids.tolist(), found, strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*out, strict=True)], ["query_id", "vec_id", "score"])

        held_ids, held = [], []
        for batch in batches:
            if batch.num_rows:
                held_ids.append(batch.column(0).to_numpy(zero_copy_only=False))
                held.append(np.array(batch.column(1).flatten()).reshape(-1, dim))
            if sum(map(len, held)) >= BLOCK_ROWS:
                yield from answer(np.concatenate(held_ids), np.concatenate(held))
                held_ids, held = [], []
        if held:
            yield from answer(np.concatenate(held_ids), np.concatenate(held))

    found = rows.select("vec_id", "v").mapInArrow(run, "query_id bigint, vec_id bigint, score double")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.select("query_id", F.row_number().over(order).cast("int").alias("rank"), "vec_id", "score").where(F.col("rank") <= k)
