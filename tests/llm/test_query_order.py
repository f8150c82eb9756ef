"""The registered language model looks further back than one word."""

from conftest import DATA


def test_op4_scores_with_order_three(spark):
    from pyspark.sql import functions as F

    from zonal.llm.language_model import held_out, score, train
    from zonal.llm.queries import op4_language_model

    docs = spark.read.parquet(f"{DATA}/sf0.001/documents.parquet")
    fit = docs.where(~held_out(F.col("doc_id")))
    got, two, three = ({r.doc_id: r.score for r in x.collect()} for x in (op4_language_model(spark, f"{DATA}/sf0.001"), score(docs, train(fit, 2)), score(docs, train(fit, 3))))
    assert got == three and got != two
