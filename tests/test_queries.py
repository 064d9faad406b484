"""Every registered query of the engine against its SQL on the smallest tables."""

import pytest

from oracle import assert_same
from skewjoin import queries


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_query_matches_sql(spark, small, name):
    assert_same(queries.QUERIES[name](spark, small), queries.ORACLES[name], small)


def test_every_query_has_sql():
    assert set(queries.ORACLES) == set(queries.QUERIES)
