"""Every query of the graph engine that has SQL returns what DuckDB returns."""

from __future__ import annotations

import pytest
from helpers import same_rows

from weftgraph.queries import ORACLE_SQL, QUERIES

ROWS_ONLY = sorted(set(QUERIES) - set(ORACLE_SQL) - {"balance_comparison"})


@pytest.mark.parametrize("name", sorted(ORACLE_SQL))
def test_matches_sql(spark, duck, sf_dir, name):
    same_rows(QUERIES[name](spark, sf_dir), duck.sql(ORACLE_SQL[name]))


@pytest.mark.parametrize("name", ROWS_ONLY)
def test_has_rows(spark, sf_dir, name):
    assert QUERIES[name](spark, sf_dir).limit(1).count() == 1


def test_entry():
    import __spark_entry__

    assert set(QUERIES) <= set(__spark_entry__.queries())
    assert set(ORACLE_SQL) <= set(__spark_entry__.oracle_sql())
