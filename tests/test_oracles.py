"""Every core query with SQL against DuckDB, on the smallest tables."""

from __future__ import annotations

import pytest

from loadshard.queries import ORACLES, QUERIES
from tests.conftest import rows_of, rows_of_sql


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_matches_sql(spark, sf, duck, name):
    assert rows_of(QUERIES[name](spark, sf)) == rows_of_sql(duck, ORACLES[name])


def test_entry_runs(spark):
    import __spark_entry__ as e

    assert e.entry(spark).columns == ["o", "c", "n"]
    assert set(e.oracle_sql()) <= set(e.queries())
