"""The pipeline's near copies by five-word similarity, against brute force."""

from itertools import combinations

import corpus_pipeline
from conftest import DATA
from test_operators import odd_docs


def shingles(text, k=5):
    words = (text or "").encode().lower().split()
    return {tuple(words[i : i + k]) for i in range(max(len(words) - k + 1, 1))} if words else set()


def similar(a, b):
    if 5 * min(len(a), len(b)) < 4 * max(len(a), len(b)):
        return False
    return not a | b or 5 * len(a & b) >= 4 * len(a | b)


def components(texts):
    sets, root = {d: shingles(t) for d, t in texts.items()}, {d: d for d in texts}

    def find(d):
        while root[d] != d:
            d = root[d]
        return d

    for a, b in combinations(sorted(texts), 2):
        if similar(sets[a], sets[b]):
            x, y = sorted((find(a), find(b)))
            root[y] = x
    return {d: find(d) for d in texts}


def test_similar_groups_equal_brute_force(spark):
    from zonal.llm.similar import similar_groups

    docs = spark.read.parquet(f"{DATA}/sf0.01/documents.parquet")
    want = components({r.doc_id: r.text for r in docs.collect()})
    assert {r.doc_id: r.component_id for r in similar_groups(docs).collect()} == want
    assert len(set(want.values())) < len({r.text for r in docs.collect()})


def test_similar_chains_and_odd_rows(spark):
    from zonal.llm.similar import similar_groups

    texts = {}
    for i in range(60):  # neighbours are similar, the ends share nothing
        texts[i] = " ".join(f"w{j}" for j in range(6 * i, 6 * i + 120))
    texts |= {100: "one two", 101: "ONE  two", 102: "one", 103: "", 104: " "}
    got = similar_groups(spark.createDataFrame(list(texts.items()), "doc_id bigint, text string")).collect()
    assert {r.doc_id: r.component_id for r in got} == components(texts)
    assert similar_groups(odd_docs(spark)).count() == odd_docs(spark).count()
    assert similar_groups(odd_docs(spark, [])).count() == 0


def test_pipeline_leaves_no_near_copies(spark):
    docs = spark.read.parquet(f"{DATA}/sf0.01/documents.parquet")
    for name, stage in corpus_pipeline.STAGES:
        if "near_dedup" in name:
            docs = stage(spark, docs, f"{DATA}/sf0.01")
    left = [shingles(r.text) for r in docs.collect()]
    assert len(left) > 700 and not any(similar(a, b) for a, b in combinations(left, 2))


def test_pages_of_one_template_and_their_copies(spark, monkeypatch):
    """A crowded bucket of different components is settled by rare shingles, not by all pairs."""
    from zonal.llm import similar

    monkeypatch.setattr(similar, "CROWD", 4)
    frame = " ".join(f"t{j}" for j in range(60))
    texts = {i: f"{frame} " + " ".join(f"p{i}x{j}" for j in range(40)) for i in range(50)}
    texts |= {100 + i: texts[i].replace(f"p{i}x7", "changed") for i in range(0, 50, 3)}
    texts |= {200 + i: texts[5].replace(f"p5x{i}", f"other{i}") for i in range(30)}
    got = similar.similar_groups(spark.createDataFrame(list(texts.items()), "doc_id bigint, text string")).collect()
    assert {r.doc_id: r.component_id for r in got} == components(texts)
