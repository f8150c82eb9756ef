"""Queries with SQL give SQL's rows on whole tables."""

import pytest
from conftest import DATA, assert_same, duck

from zonal.llm.queries import ORACLE_SQL, QUERIES


@pytest.mark.parametrize("name", sorted(ORACLE_SQL))
def test_equals_sql(spark, name):
    assert assert_same(QUERIES[name](spark, f"{DATA}/sf0.01"), duck(), ORACLE_SQL[name]) > 0
