"""Every registered query that has SQL gives the SQL's rows; the others run."""

import pytest
from checks import SMALL, same_rows

from setstream.plans import catalog

SLOW = {"rmse_planted", "neighbourhood_quality"}


@pytest.mark.parametrize("name", sorted(catalog.ORACLES))
def test_query_matches_sql(spark, duck, name):
    same_rows(catalog.QUERIES[name](spark, SMALL), duck, catalog.ORACLES[name])


@pytest.mark.parametrize("name", sorted(set(catalog.QUERIES) - set(catalog.ORACLES) - SLOW))
def test_query_without_sql_runs(spark, name):
    df = catalog.QUERIES[name](spark, SMALL)
    assert len(df.collect()) >= 1


def test_entry(spark):
    import __spark_entry__

    df = __spark_entry__.entry(spark)
    assert df.columns == ["a", "b", "est"]
    assert df.count() >= 0
