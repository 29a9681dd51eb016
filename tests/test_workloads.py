import pytest

from helpers import DATA, same
from rasterchain import workloads

#: Slow on whole documents; their operators are covered by others on smaller rasters.
SLOW = {"open_rec75_strip", "stream_hmax"}
NAMES = sorted(n for n in workloads.ORACLES if n not in SLOW)


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_its_oracle(name, spark, duck):
    assert same(workloads.QUERIES[name](spark, DATA).toPandas(), duck.sql(workloads.ORACLES[name]).df())


@pytest.mark.parametrize("name", sorted(set(workloads.QUERIES) - set(workloads.ORACLES)))
def test_query_without_oracle_runs(name, spark):
    assert workloads.QUERIES[name](spark, DATA).count() > 0
