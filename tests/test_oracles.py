"""Every query beside its oracle on the smallest tables (the recursive ones run at a larger scale in oracle_check.py)."""

import pytest
from oracle_check import compare, connect

from temporal_rules.workloads import oracle, queries

SLOW = {"own_temporal_naive"}  # it evaluates everything in every round, which is what it is for


@pytest.fixture(scope="module")
def con(sf):
    return connect(sf)


@pytest.mark.parametrize("name", [n for n in oracle.SQL if n not in SLOW])
def test_query_equals_oracle(spark, sf, con, name):
    assert compare(spark, con, name, queries.QUERIES[name], oracle.SQL[name], sf) is None


def test_every_query_has_an_oracle():
    assert set(oracle.SQL) == set(queries.QUERIES)
