"""Every registered query against its oracle at sf0.01, as the driver does; queries without oracle must run."""

import pytest

from assocmine import queries
from tests.compare import connect, same

SF = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def con():
    return connect(SF)


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_oracle(spark, con, name):
    same(queries.QUERIES[name](spark, SF), queries.ORACLES[name], con)


#: 160 searches among 63 to 93 attributes each; tests/test_workloads.py runs the same code on fewer.
LONG = {"q_runtime_large", "q_runtime_large_class"}


@pytest.mark.parametrize("name", sorted(set(queries.QUERIES) - set(queries.ORACLES) - LONG))
def test_runs(spark, name):
    assert queries.QUERIES[name](spark, SF).count() >= 0
