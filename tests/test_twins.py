"""Every query with SQL gives the rows of its DuckDB twin."""

import pytest

import __spark_entry__ as entry_point
from tests.twins import assert_twin
from vecroute.registry import ORACLES, QUERIES


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_twin(spark, sf, name):
    assert_twin(spark, sf, QUERIES[name], ORACLES[name])


def test_entry(spark):
    df = entry_point.entry(spark)
    assert df.columns == ["query_id", "rank", "item_id", "score"] and df.count() > 0
    assert set(entry_point.oracle_sql()) <= set(entry_point.queries())


def test_expected_curves(spark, sf01):
    """Fixed-ingredient values known for these tables."""
    got = {r.branching: round(r.access_rate, 3) for r in QUERIES["access_rate_curve"](spark, sf01).collect()}
    assert got == {1: 0.1, 5: 0.438, 10: 0.704, 20: 0.930, 50: 1.0}
    got = {r.branching: round(r.precision, 4) for r in QUERIES["precision_curve_exact_sub"](spark, sf01).collect()}
    assert got == {1: 0.3197, 5: 0.6521, 10: 0.8380, 20: 0.9718, 50: 1.0}
