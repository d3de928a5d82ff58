"""Every query against its DuckDB text on the smallest tables."""

import pytest

from calseries.queries import ORACLES, QUERIES

from .conftest import SMALL, canon


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_equals_oracle(spark, duck, name):
    got, want = QUERIES[name](spark, SMALL).toPandas(), duck.execute(ORACLES[name]).fetchdf()
    assert sorted(got.columns) == sorted(want.columns)
    assert canon(got) == canon(want)


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES)))
def test_without_oracle_runs(spark, name):
    assert QUERIES[name](spark, SMALL).count() > 0
