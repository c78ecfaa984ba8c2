"""Queries against their SQL at the smallest scale, and the driver contract."""

import pytest

import __spark_entry__ as contract
from reuse_engine.plans.catalog import ORACLES, QUERIES
from tests.conftest import SMALL

@pytest.mark.parametrize("name", sorted(ORACLES))
def test_equals_sql(spark, duck, same_rows, name):
    same_rows(QUERIES[name](spark, SMALL), duck.sql(ORACLES[name]).df())


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES)))
def test_runs(spark, name):
    assert QUERIES[name](spark, SMALL).count() >= 0


def test_contract(spark):
    assert set(contract.oracle_sql()) <= set(contract.queries())
    df = contract.entry(spark)
    assert df.count() > 0 and df.columns[:2] == ["corpus", "origin"]


def test_worked_example_scores_88(spark):
    row = contract.queries()["w20_worked_example"](spark, SMALL).first()
    assert (row["dist"], row["max_len"], row["score_bp"]) == (3, 25, 8800)
