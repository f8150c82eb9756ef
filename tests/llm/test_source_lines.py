"""Repeated lines of a source: long ones go well below a tenth of its documents, short ones stay."""

import corpus_pipeline
from conftest import DATA


def test_repeated_long_lines_go_and_short_ones_stay(spark):
    long, short, rare = "this long line stands on many of our pages", "All rights.", "this other long line stands on few pages here"
    rows = [(i, f"own {i}\n" + (f"{long}\n{short}" if i % 25 == 0 else rare if i < 4 else "x"), "en", "s", 1) for i in range(400)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    got = {r.doc_id: r.text for r in corpus_pipeline.line_dedup_by_source(spark, docs, f"{DATA}/sf0.001").collect()}
    assert len(got) == 400 and not any(long in t for t in got.values())
    assert got[25] == f"own 25\n{short}" and got[1] == f"own 1\n{rare}"


def test_the_corpus_line_goes_from_every_source(spark):
    docs = spark.read.parquet(f"{DATA}/sf0.1/documents.parquet")
    line = "The and attion to thanedble the, anea. Eriner thanea."
    assert docs.where(docs.text.contains(line)).count() > 1000
    out = corpus_pipeline.line_dedup_by_source(spark, docs, f"{DATA}/sf0.1")
    assert not [t for (t,) in out.select("text").where(out.text.contains(line)).collect() if line in map(str.strip, t.split("\n"))]
    assert out.count() == docs.count()
