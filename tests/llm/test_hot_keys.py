"""Hot keys are dealt over many tasks without changing a row; scratch tables can be deleted."""

import random

import pytest


@pytest.fixture
def small_pieces(monkeypatch):
    from zonal.llm import common

    monkeypatch.setattr(common, "HOT_ROWS", 20)
    monkeypatch.setattr(common, "HOT_KEYS", 10)


@pytest.mark.parametrize("how", ["inner", "left"])
def test_join_by_key_equals_a_plain_join(spark, small_pieces, how):
    from pyspark.sql import functions as F

    from zonal.llm.common import join_by_key, materialize

    rows = spark.range(2000).select(F.col("id"), F.when(F.col("id") % 3 == 0, 0).otherwise(F.col("id") % 200).alias("k"))
    table = materialize(rows.where("k <> 7").groupBy("k").agg(F.count(F.lit(1)).alias("n"), F.min("id").alias("m")), "t")
    got = join_by_key(rows, table, ["k"], "n", ["id"], how)
    plan = got._jdf.queryExecution().toString()
    assert "__pieces" in plan  # the hot key was dealt out
    assert sorted(map(tuple, got.select("id", "k", "n", "m").collect()), key=repr) == sorted(map(tuple, rows.join(table, "k", how).select("id", "k", "n", "m").collect()), key=repr)


def test_operators_with_hot_groups(spark, small_pieces):
    from zonal.llm.components import connected_components
    from zonal.llm.exact_dedup import exact_groups
    from zonal.llm.simhash import near_duplicates

    links = [(0, i) for i in range(1, 400)] + [(500 + i, 501 + i) for i in range(50)]
    random.Random(1).shuffle(links)
    got = dict(map(tuple, connected_components(spark.createDataFrame(links, "a bigint, b bigint").repartition(8)).collect()))
    assert got == {**{i: 0 for i in range(1, 400)}, **{501 + i: 500 for i in range(50)}}
    docs = spark.createDataFrame([(i, "the same words again" if i % 3 else f"own words of text number {i}") for i in range(900)], "doc_id bigint, text string")
    assert all((r.keep_id, r.group_size) == ((899, 600) if r.doc_id % 3 else (r.doc_id, 1)) for r in exact_groups(docs, keep="largest").collect())
    assert all(r.component_id == 1 for r in near_duplicates(docs).collect() if r.doc_id % 3)


def test_discard_deletes_files(spark):
    import os

    from zonal.llm.common import discard, materialize

    table = materialize(spark.range(5), "t")
    path = table._kept_at.removeprefix("file://")
    assert os.path.isdir(path)
    discard(table, spark.range(2))
    assert not os.path.exists(path)


def test_shared_folder_is_asked_for_on_a_cluster():
    from zonal.llm.common import shared_dir

    class Session:
        class conf:
            get = staticmethod(lambda name, default=None: None)

        class sparkContext:
            master = "spark://somewhere:7077"

    with pytest.raises(RuntimeError, match="spark.checkpoint.dir"):
        shared_dir(Session)
