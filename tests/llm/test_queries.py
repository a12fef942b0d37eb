import pytest

from tests.oracle import same
from veil.llm import queries as Q


@pytest.mark.parametrize("name", sorted(Q.ORACLES))
def test_query_equals_sql(spark, name):
    same(spark, name, Q.QUERIES, Q.ORACLES)
