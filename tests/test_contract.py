import pytest
from comparing import same

from spurline import queries_graphs, queries_more  # noqa: F401 - they register queries
from spurline.queries import ORACLES, QUERIES


@pytest.mark.parametrize("name", ORACLES)
def test_sql(spark, name):
    assert same(QUERIES[name](spark, "/root/testdata/sf0.001"), ORACLES[name], "/root/testdata/sf0.001") > 0


def test_driver_contract(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 1500
    assert set(e.oracle_sql()) <= set(e.queries())
