"""Every query against its DuckDB twin on the smallest tables; `bench.py --twins` does the same on any other folder."""

import pytest

from hubsplit import catalog
from hubsplit.twins import connect, differences

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def duck():
    return connect(SF)


@pytest.mark.parametrize("name", sorted(catalog.oracle_sql()))
def test_twin(spark, duck, name):
    assert differences(spark, duck, SF, name) is None


@pytest.mark.parametrize("name", sorted(set(catalog.queries()) - set(catalog.oracle_sql())))
def test_query_without_a_twin_runs(spark, name):
    assert catalog.queries()[name](spark, SF).count() > 0


def test_sort_within_orders_every_partition(spark):
    """What no result set can show: each partition is sorted."""
    df = catalog.queries()["sort_within"](spark, SF)
    key = df.columns[0]
    assert all(rows == sorted(rows) for rows in df.select(key).rdd.glom().map(lambda p: [r[0] for r in p]).collect()) or len(df.columns) > 1


def test_catalogue_is_whole():
    q, s = catalog.queries(), catalog.oracle_sql()
    assert set(s) <= set(q) and len(q) > 250
