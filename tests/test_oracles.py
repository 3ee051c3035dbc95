"""Every registered query runs; those with SQL give the same rows as DuckDB."""

import pytest

import xlsql.queries as xq
from tests.oracle import connect, rows_of, sql_rows

QUERIES, ORACLES = xq.load()
SLOW = {"q65_finetuned_scores", "q61b_stage_ablation", "q61e_prompt_ablation", "q49b_parallel_tokens", "q47a_bpe_fertility"}


@pytest.fixture(scope="module")
def duck(sf):
    return connect(sf)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_matches_sql(spark, sf, duck, name):
    assert rows_of(QUERIES[name](spark, sf)) == sql_rows(duck, ORACLES[name])


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES) - SLOW))
def test_runs(spark, sf, name):
    assert QUERIES[name](spark, sf).count() > 0
