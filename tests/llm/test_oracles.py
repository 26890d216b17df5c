"""The operators' queries that SQL can express, on the given tables."""

import pytest
from oracle import connect, same

from simweave.llm.queries import ORACLES, QUERIES


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_oracle(spark, name):
    d = "/root/testdata/sf0.001"
    assert same(QUERIES[name](spark, d), connect(d).execute(ORACLES[name]))
