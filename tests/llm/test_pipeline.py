"""Every pipeline stage against a plain computation on its own input."""

from collections import Counter, defaultdict

import corpus_pipeline
from conftest import DATA

SF = f"{DATA}/sf0.001"


def rows(df):
    return [r.asDict() for r in df.collect()]


def test_stages_on_their_inputs(spark):
    from zonal.llm.common import materialize
    from test_similar import components

    from zonal.llm.queries import LINE_PAGES

    docs, seen = spark.read.parquet(f"{SF}/documents.parquet"), {}
    for name, stage in corpus_pipeline.STAGES:
        before = docs
        docs = materialize(stage(spark, docs, SF), name)
        seen[name] = (before, docs)
        if name != "packing":
            assert docs.columns == before.columns
    before, after = (rows(x) for x in seen["quality_classifier"])
    assert {r["doc_id"] for r in after} <= {r["doc_id"] for r in before} and len(after) > 0.6 * len(before)

    before, after = (rows(x) for x in seen["line_dedup"])
    pages, count = Counter(r["source"] for r in before), Counter()
    for r in before:
        count.update((r["source"], x) for x in {x.strip(" ") for x in r["text"].split("\n")} if x)
    ratio, words = corpus_pipeline.SOURCE_RATIO, corpus_pipeline.LINE_WORDS
    bad = {k for k, n in count.items() if n >= LINE_PAGES and n > pages[k[0]] * ratio and len(k[1].split()) >= words}
    want = {r["doc_id"]: "\n".join(x for x in r["text"].split("\n") if (r["source"], x.strip(" ")) not in bad) for r in before}
    assert {r["doc_id"]: r["text"] for r in after} == want

    before, after = (rows(x) for x in seen["simhash_near_dedup"])
    root = components({r["doc_id"]: r["text"] for r in before})  # five words, 0.8 or more
    assert {r["doc_id"] for r in after} == {d for d in root if root[d] == d} and len(after) < len(before)

    before, after = (rows(x) for x in seen["mix_sources"])
    size = defaultdict(int)
    for r in before:
        size[r["source"]] += len(r["text"].split())
    copies = Counter(r["doc_id"] for r in after)
    assert max(copies.values()) <= 2
    taken = sum(len(r["text"].split()) for r in after)
    assert abs(taken - 1.5 * sum(size.values())) < 0.15 * sum(size.values())

    before, after = (rows(x) for x in seen["packing"])
    assert Counter(r["doc_id"] for r in after if r["start"] == 0) == Counter(r["doc_id"] for r in before)
    fill = Counter()
    for r in after:
        fill[r["sequence_id"]] += r["length"]
    assert max(fill.values()) <= 2048


def test_stages_are_the_five_in_order():
    assert [name for name, _ in corpus_pipeline.STAGES] == ["quality_classifier", "line_dedup", "simhash_near_dedup", "mix_sources", "packing"]


def test_run_applies_all_stages(spark):
    got = corpus_pipeline.run(spark, SF)
    assert got.count() > 0 and "sequence_id" in got.columns


def test_stages_on_odd_rows(spark):
    from test_operators import ODD, odd_docs

    for name, stage in corpus_pipeline.STAGES:
        for docs in (odd_docs(spark), odd_docs(spark, [])):
            out = stage(spark, docs, SF)
            n = out.count()
            assert name == "packing" or out.columns == docs.columns
            assert n > 0 or docs.isEmpty()
            if name == "line_dedup":
                assert n == (0 if docs.isEmpty() else len(ODD))
