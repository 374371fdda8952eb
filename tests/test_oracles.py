import pytest

from tests.oracle import assert_same
from vintage import workloads


@pytest.mark.parametrize("name", sorted(workloads.ORACLE_SQL))
def test_query_equals_its_sql(spark, sf, name):
    assert_same(spark, sf, workloads.QUERIES[name], workloads.ORACLE_SQL[name])


def test_every_sql_has_a_query():
    assert workloads.ORACLE_SQL.keys() <= workloads.QUERIES.keys()
