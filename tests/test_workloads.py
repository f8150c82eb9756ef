"""Every workload query gives the rows of its brute-force SQL."""

import pytest
from conftest import DATA, assert_same, duck

import zonal.relational  # noqa: F401  (registers its queries)
from zonal.workloads import ORACLE_SQL, QUERIES


@pytest.mark.parametrize("name", sorted(ORACLE_SQL))
def test_equals_sql(spark, name):
    assert assert_same(QUERIES[name](spark, f"{DATA}/sf0.001"), duck("sf0.001"), ORACLE_SQL[name]) >= 0
