"""Every query that has an oracle gives the oracle's rows; the others run and give rows of a stable schema."""

import pytest
from oracle import connect, same

from simweave.queries import load

D = "/root/testdata/sf0.001"
QUERIES, ORACLES = load()
#: Many joins each; test_survey_workloads.py runs what they are made of.
SLOW = {"a01_timing", "w02_methods", "w03_methods", "w04_methods", "w05_fastest_variant", "w06_recall", "w07_error_shares", "w08_pruning_curves", "w09_sweep_cost", "w10_sweep_quality", "w12_ablations", "w12_priors", "w12_inference_savers"}


@pytest.fixture(scope="module")
def duck():
    return connect(D)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_oracle(spark, duck, name):
    assert same(QUERIES[name](spark, D), duck.execute(ORACLES[name]))


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES) - SLOW))
def test_rows(spark, name):
    frame = QUERIES[name](spark, D)
    assert len(set(frame.columns)) == len(frame.columns) and frame.count() >= 0


def test_entry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())
