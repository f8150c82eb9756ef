"""One local session, and a comparison of Spark's rows with DuckDB's."""

from __future__ import annotations

import os
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parent.parent
sys.path.insert(0, str(ROOT))
DATA = Path(os.environ.get("TEST_DATA", "/root/testdata"))
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    session = (
        SparkSession.builder.master("local[8]")
        .config("spark.sql.shuffle.partitions", "8")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "8g")
        .getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    from zonal.workers import let_workers_import

    let_workers_import(session)
    yield session
    session.stop()


def duck(sf: str = "sf0.01"):
    import duckdb

    con = duckdb.connect()
    con.execute("set timezone = 'UTC'")
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{DATA}/{sf}/{t}.parquet'")
    return con


def canon(v):
    if isinstance(v, float):
        return float(f"{v:.10g}")
    if isinstance(v, list | tuple):
        return tuple(canon(x) for x in v)
    return v


def assert_same(df, con, sql: str) -> int:
    """Equal column names and equal rows, in any order."""
    cols = sorted(df.columns)
    mine = sorted((tuple(canon(r[c]) for c in cols) for r in df.collect()), key=repr)
    cur = con.execute(sql)
    names = [d[0] for d in cur.description]
    assert sorted(names) == cols
    at = [names.index(c) for c in cols]
    theirs = sorted((tuple(canon(r[i]) for i in at) for r in cur.fetchall()), key=repr)
    assert len(mine) == len(theirs)
    wrong = [(a, b) for a, b in zip(mine, theirs, strict=True) if a != b]
    assert not wrong, wrong[:3]
    return len(mine)
