"""Every query with SQL against DuckDB on the smallest tables."""

import pytest

from filterfleet import catalogue
from tests.conftest import SF


@pytest.mark.parametrize("name", sorted(catalogue.ORACLES))
def test_query(spark, oracle, name):
    df = catalogue.QUERIES[name](spark, SF)
    columns, want = oracle(catalogue.ORACLES[name])
    assert sorted(df.columns) == columns
    assert sorted(repr(list(r)) for r in df.select(*columns).collect()) == want


def test_queries_without_sql_run(spark):
    for name in set(catalogue.QUERIES) - set(catalogue.ORACLES):
        assert catalogue.QUERIES[name](spark, SF).count() > 0
