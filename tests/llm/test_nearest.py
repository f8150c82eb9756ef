"""Collision counting verifies candidates only, and these are a small share of all rows."""

import numpy as np
import pytest
from conftest import DATA


def vectors(name):
    import pyarrow.parquet as pq

    t = pq.read_table(f"{DATA}/{name}/embeddings.parquet", columns=["vec_id", "embedding"])
    x = np.array(t["embedding"].combine_chunks().flatten()).reshape(t.num_rows, -1).astype(float)
    return t["vec_id"].to_numpy(), x


@pytest.mark.parametrize("rows", [500, 2000, 10_000])
def test_share_of_candidates_and_recall(rows):
    from zonal.llm.nearest import BlockIndex, needed

    ids, x = vectors("check_s" if rows > 2000 else "sf0.1")
    ids, x = ids[:rows], x[:rows]
    q = np.flatnonzero(ids % 20 == 0)[:100]
    lines = np.random.default_rng(11).standard_normal((96, x.shape[1] + 1))
    index = BlockIndex(x, lines, float(np.linalg.norm(x, axis=1).max()))
    own = [np.array([i]) for i in q]
    found = index.search(x[q], x[q] @ lines[:, :-1].T, own, 20, needed(96, 3.0, 1.7), index.radius(x[q], 20), 1.03, 1.0, 3.0)
    hits = verified = 0
    for i, (places, scores) in zip(q, found, strict=True):
        exact = x @ x[i]
        assert scores == pytest.approx(exact[places], rel=1e-12) and i not in places and len(set(places.tolist())) == len(places)
        exact[i] = -np.inf
        hits += len(set(np.argsort(-exact, kind="stable")[:20].tolist()) & set(places[np.argsort(-scores, kind="stable")[:20]].tolist()))
        verified += len(places)
    share = verified / len(q) / rows
    print(f"rows {rows}: candidates {share:.3f}, recall {hits / 20 / len(q):.3f}")
    assert hits / 20 / len(q) >= 0.93 and share < {500: 0.85, 2000: 0.6, 10_000: 0.45}[rows]


def test_collisions_are_counted_alike_from_either_side():
    from zonal.llm.nearest import BlockIndex

    r = np.random.default_rng(1)
    x, lines = r.standard_normal((300, 8)), r.standard_normal((20, 9))
    index = BlockIndex(x, lines, float(np.linalg.norm(x, axis=1).max()))
    rest = np.sqrt(np.maximum(index.square - (x * x).sum(1), 0))
    at, q = x @ lines[:, :-1].T + rest[:, None] * lines[:, -1], (x[:1] @ lines[:, :-1].T)
    for half in (0.1, 1.0, 5.0, 50.0):
        lo, hi = index.windows(q, half)
        assert np.array_equal(index.collisions(lo[0], hi[0]), (np.abs(at - q[0]) <= half).sum(1))


def test_ties_over_blocks_and_repeated_ids(spark, monkeypatch):
    from pyspark.sql import functions as F

    from zonal.llm import nearest as nn

    monkeypatch.setattr(nn, "BLOCK_ROWS", 7)
    rows = [(i, [1.0, 2.0, 0.5]) for i in range(1, 40)] + [(20, [3.0, 0.0, 0.0]), (40, [0.0, 1.0, 0.0])]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>").repartition(3)
    got = nn.nearest(df, F.col("vec_id") % 20 == 0, k=5, query_block=1).collect()
    mine = sorted((r.query_id, r.rank, r.vec_id) for r in got)
    assert [v for q, _, v in mine if q == 40] == [1, 2, 3, 4, 5]  # equal scores: smaller ids
    assert [v for q, _, v in mine if q == 20] == [1, 2, 3, 4, 5] and len(mine) == 10  # one of its rows asks


def test_memory_of_many_queries_is_bounded(monkeypatch):
    """Candidates of all queries of a file together once filled an executor's memory."""
    import tracemalloc

    from zonal.llm import nearest as nn

    ids, x = vectors("sf0.1")
    lines = np.random.default_rng(11).standard_normal((96, x.shape[1] + 1))
    index = nn.BlockIndex(x, lines, float(np.linalg.norm(x, axis=1).max()))
    own, at = [np.array([i]) for i in range(len(x))], x @ lines[:, :-1].T
    how = (20, nn.needed(96, 3.0, 1.7), index.radius(x, 20), 1.03, 1.0, 3.0)
    whole = index.search(x[:100], at[:100], own[:100], *how)
    monkeypatch.setattr(nn, "CANDIDATES", 20_000)
    tracemalloc.start()
    got = list(index.best(x, at, own, ids, *how))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert len(got) == len(x) and peak < 10e6  # 2,000 queries of about 900 candidates each: 29 MB at once
    for (best, scores), (places, all_scores) in zip(got[:100], whole, strict=True):
        order = np.lexsort((ids[places], -all_scores))[:20]
        assert np.array_equal(best, ids[places[order]]) and np.allclose(scores, all_scores[order])


def test_wider_windows_count_what_they_gain():
    from zonal.llm.nearest import BlockIndex

    r = np.random.default_rng(2)
    x, lines = r.standard_normal((300, 8)), r.standard_normal((20, 9))
    index = BlockIndex(x, lines, float(np.linalg.norm(x, axis=1).max()))
    lo, hi = index.windows(x[:1] @ lines[:, :-1].T, 0.5)
    more = index.windows(x[:1] @ lines[:, :-1].T, 1.5)
    assert np.array_equal(index.widened(index.collisions(lo[0], hi[0]), lo[0], hi[0], more[0][0], more[1][0]), index.collisions(more[0][0], more[1][0]))


def test_blocks_of_copies_take_few_rounds(monkeypatch):
    """Fewer copies of a query than k: the typical radius is 0, its k-th neighbour is far."""
    from zonal.llm import nearest as nn

    ids, x = vectors("sf0.1")
    x = np.tile(x[:1000], (20, 1))
    lines = np.random.default_rng(11).standard_normal((96, x.shape[1] + 1))
    index = nn.BlockIndex(x, lines, float(np.linalg.norm(x, axis=1).max()))
    rounds, windows = [], nn.BlockIndex.windows
    monkeypatch.setattr(nn.BlockIndex, "windows", lambda *a: rounds.append(1) or windows(*a))
    found = list(index.best(x[:40], x[:40] @ lines[:, :-1].T, [np.array([i]) for i in range(40)], np.arange(len(x)), 20, nn.needed(96, 3.0, 1.7), index.radius(x, 20), 1.03, 1.0, 3.0))
    for i, (best, _) in enumerate(found):
        assert len(best) == 20 and set(range(i + 1000, len(x), 1000)) <= set(best.tolist())
    assert len(rounds) < 60  # over 260 when every round widened by 3 % from 0
