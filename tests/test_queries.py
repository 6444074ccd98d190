"""Every query with SQL gives the rows that DuckDB gives; the others run."""

from __future__ import annotations

import pytest

from stepsql.queries import ORACLE_SQL, QUERIES

from .oracle import duck_rows, spark_rows


@pytest.mark.parametrize("name", sorted(ORACLE_SQL))
def test_matches_sql(spark, data, name):
    assert spark_rows(QUERIES[name](spark, data)) == duck_rows(ORACLE_SQL[name], data)


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLE_SQL)))
def test_runs(spark, data, name):
    assert QUERIES[name](spark, data).count() > 0
