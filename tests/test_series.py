"""Series of joins run one by one."""

import pytest

from setsim.functions.bitmap import BitmapSpec
from setsim.operators.order import prepare
from setsim.plans import experiments
from tests.test_joins import _long, _sets


@pytest.fixture(scope="module")
def some(spark):
    return prepare(_long(spark, _sets(3, n=60, universe=60, most=14)))


@pytest.mark.parametrize("series", [
    lambda c: experiments.result_sizes(c, ("0.5", "0.8")),
    lambda c: experiments.ratios({"x": c}, ("0.5", "0.8"), BitmapSpec("xor", 64, cutoff=None)),
    lambda c: experiments.ratios_by_shape(c, "0.5", [("or", 64), ("xor", 64)]),
    lambda c: experiments.verified_pairs({"x": c}),
])
def test_joins_of_a_series_run_one_by_one(some, series):
    """The table of a series reads finished sums: no two of its joins have shuffle files at a time."""
    df = series(some)
    assert "Exchange" not in df._jdf.queryExecution().executedPlan().toString()
    assert df.count() >= 2 and df.inputFiles()
