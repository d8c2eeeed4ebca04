"""Every registered query with SQL against DuckDB on the smallest tables."""

import pytest

from chartrel.plans.queries import ORACLES, QUERIES

from .conftest import duck_rows, rows_of


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_equals_sql(spark, duck, small, name):
    assert rows_of(QUERIES[name](spark, small)) == duck_rows(duck, ORACLES[name])
