"""Each registered query of the engine against its SQL, on the smallest tables."""

import pytest

from segcompare import oracle, queries

from .compare import connect, differences

SMALL = "/root/testdata/sf0.001"
ALL, SQL = queries.queries(), oracle.oracle_sql()


@pytest.fixture(scope="module")
def con():
    return connect(SMALL)


def test_registry_is_whole():
    assert SQL.keys() <= ALL.keys()
    assert ALL.keys() - SQL.keys() == {"hilbert_keys", "tree_levels", "work_scale", "work_threshold", "rebalance_sim", "late_rows", "io_generated", "io_wkb"}


@pytest.mark.parametrize("name", sorted(SQL))
def test_query_equals_sql(spark, con, name):
    assert differences(ALL[name](spark, SMALL), con, SQL[name]) is None


@pytest.mark.parametrize("name", sorted(ALL.keys() - SQL.keys()))
def test_query_has_rows(spark, name):
    assert ALL[name](spark, SMALL).count() > 0
