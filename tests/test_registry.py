"""Every query with SQL gives that SQL's rows; the others run."""

import pytest

from shapebalance.plans import registry

from .conftest import SF, plain

SLOW = {"kernel_sweep", "fit_measured", "benchmark_measured"}  # the first and last run on fewer sizes in test_whole_runs.py and test_methods.py


@pytest.mark.parametrize("name", sorted(registry.ORACLES))
def test_matches_sql(spark, duck, name):
    got, want = registry.QUERIES[name](spark, SF).toPandas(), duck.execute(registry.ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert plain(got) == plain(want)


@pytest.mark.parametrize("name", sorted(set(registry.QUERIES) - set(registry.ORACLES) - SLOW))
def test_runs(spark, name):
    assert registry.QUERIES[name](spark, SF).count() > 0
