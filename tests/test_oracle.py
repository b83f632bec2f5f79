"""Every registered query with SQL, against DuckDB on the same tables."""

from __future__ import annotations

import pytest

from groupsearch.plans import registry

from .conftest import MEDIUM, SMALL

SQL = registry.oracle_sql()
QUERIES = registry.queries()


@pytest.mark.parametrize("name", sorted(SQL))
def test_same_rows_as_sql(name, spark, same_as_sql):
    assert same_as_sql(QUERIES[name], SQL[name], spark, SMALL if name != "roc_documents" else MEDIUM) >= 0


def test_every_sql_has_its_query():
    assert set(SQL) <= set(QUERIES)
