import pytest
from gossipkit import oracles, queries
from oracle import same


@pytest.mark.parametrize("name", sorted(oracles.ORACLES))
def test_query_equals_sql(spark, sf, name):
    same(spark, sf, queries.QUERIES[name], oracles.ORACLES[name])
