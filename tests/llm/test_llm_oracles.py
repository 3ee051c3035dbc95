"""Operators that SQL can express, against DuckDB."""

import pytest

from tests.oracle import connect, rows_of, sql_rows
from xlsql.llm.registry import ORACLES, QUERIES


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_matches_sql(spark, sf, name):
    assert rows_of(QUERIES[name](spark, sf)) == sql_rows(connect(sf), ORACLES[name])
