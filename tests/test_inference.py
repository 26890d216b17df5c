"""Posterior mathematics and decision tables against exact arithmetic, published counts and simulation."""

import math
from fractions import Fraction

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from simweave.functions.beta import binom_pmf, reg_inc_beta
from simweave.functions.posterior import BetaPosterior, GridPosterior, TruncatedPosterior, angular_to_cosine, beta_from_moments, cosine_to_angular
from simweave.operators.candidates import num_bands
from simweave.plans.decision import ACCEPT, JoinParams, classical_hashes_needed, decision_table, min_matches, prune_probability, required_cap

J, C = BetaPosterior(), TruncatedPosterior()


def tail(t: Fraction, m: int, n: int) -> Fraction:
    return sum(math.comb(n + 1, i) * t**i * (1 - t) ** (n + 1 - i) for i in range(m + 1))


@given(st.integers(1, 60), st.integers(0, 60), st.integers(1, 99))
@settings(max_examples=100, deadline=None)
def test_tail_equals_exact_sum(n, m, percent):
    m = min(m, n)
    t = Fraction(percent, 100)
    assert J.prob_ge(float(t), m, n) == pytest.approx(float(tail(t, m, n)), rel=1e-9, abs=1e-300)


def test_incomplete_beta_ends_and_symmetry():
    assert reg_inc_beta(0, 2, 3) == 0 and reg_inc_beta(1, 2, 3) == 1
    assert reg_inc_beta(0.3, 2.5, 4.5) == pytest.approx(1 - reg_inc_beta(0.7, 4.5, 2.5), rel=1e-12)
    assert sum(binom_pmf(m, 20, 0.3) for m in range(21)) == pytest.approx(1)


def test_goldens():
    assert J.prob_ge(0.7, 18, 32) == pytest.approx(0.043739, abs=1e-6)
    assert (J.prob_ge(0.7, 45, 64), J.concentration(0.05, 45, 64), J.mode(45, 64)) == pytest.approx((0.492743, 0.624849, 0.703125), abs=1e-6)
    assert (C.prob_ge(0.7, 45, 64), C.concentration(0.05, 45, 64), C.estimate(45, 64)) == pytest.approx((0.191148, 0.274842, 0.595699), abs=1e-6)
    assert [min_matches(J, 0.7, 0.03, n, n)[0] for n in (32, 64, 128, 256)] == [18, 38, 80, 166]
    assert [min_matches(C, 0.7, 0.03, n, n)[0] for n in (32, 64, 128, 256)] == [20, 42, 87, 179]
    assert [required_cap(J, JoinParams(t)) for t in (0.3, 0.5, 0.7)] == [480, 480, 448]
    assert [required_cap(C, JoinParams(t)) for t in (0.5, 0.7, 0.9)] == [3360, 2080, 704]
    assert J.prob_ge(0.8, 10, 100) == pytest.approx(5.2e-52, rel=0.02) and C.prob_ge(0.8, 10, 100) == pytest.approx(5.1e-34, rel=0.02)


def test_classical_hash_counts():
    assert classical_hashes_needed(0.5, 0.05, 0.05)[1] == 361 and classical_hashes_needed(0.95, 0.05, 0.05)[1] == 31
    assert classical_hashes_needed(0.5, 0.05, 0.05, "inward")[0] == 371 and classical_hashes_needed(0.95, 0.05, 0.05, "inward")[1] == 70


def test_band_counts():
    assert [num_bands(t, 3, 0.03) for t in (0.3, 0.5, 0.7, 0.9)] == [129, 27, 9, 3]
    assert [num_bands(t, 8, 0.03, "cosine") for t in (0.5, 0.7, 0.9)] == [89, 35, 11]


@given(st.floats(0.0, 1.0))
def test_angular_map_inverts(c):
    assert angular_to_cosine(cosine_to_angular(c)) == pytest.approx(c, abs=1e-7)


def test_cosine_estimate_is_clamped_and_tail_survives_underflow():
    assert C.estimate(3, 64) == pytest.approx(0, abs=1e-12)
    assert 0 <= C.prob_ge(0.9, 5, 1024) < 1e-100


def test_probability_rises_with_matches_and_table_is_consistent():
    for posterior in (J, C):
        values = [posterior.prob_ge(0.7, m, 64) for m in range(65)]
        assert all(a <= b + 1e-15 for a, b in zip(values, values[1:]))
        table = decision_table(posterior, JoinParams(0.7, cap=128))
        for n, m, verdict, _, prob, conc in table.rows():
            assert prob >= 0.03 and (verdict == ACCEPT) == (conc >= 0.97)


def test_total_agreement_is_accepted_at_the_known_round():
    j, c = decision_table(J, JoinParams(0.7)), decision_table(C, JoinParams(0.7))
    assert [j.verdict(n, n) == ACCEPT for n in (32, 64, 96)] == [False, False, True]
    assert c.verdict(32, 32) == ACCEPT


def test_grid_posterior_agrees_with_conjugate():
    g = GridPosterior(lambda s: s * 0 + 1, 0, 1, 20000)
    assert g.prob_ge(0.6, 30, 50) == pytest.approx(J.prob_ge(0.6, 30, 50), abs=1e-4)
    assert g.mode(30, 50) == pytest.approx(0.6, abs=1e-3)


def test_prior_by_moments():
    assert beta_from_moments(0.5, 0.0) == (1, 1) == beta_from_moments(None, None) == beta_from_moments(0.5, 0.3)
    a, b = beta_from_moments(0.3, 0.02)
    assert a / (a + b) == pytest.approx(0.3) and a * b / ((a + b) ** 2 * (a + b + 1)) == pytest.approx(0.02)


@pytest.mark.parametrize("bad", [{"t": 0}, {"t": 1}, {"t": 0.5, "eps": 0}, {"t": 0.5, "delta": 1}, {"t": 0.5, "gamma": 0}, {"t": 0.5, "step": 0}])
def test_parameters_are_validated(bad):
    with pytest.raises(ValueError):
        JoinParams(**bad)


def test_accepted_estimates_are_accurate_often_enough():
    """Similarities from the prior, matches from the similarity: accepted walks that are off by delta stay under gamma plus noise."""
    rng = np.random.default_rng(1)
    table = decision_table(J, JoinParams(0.5))
    off = accepted = 0
    for s in rng.uniform(0, 1, 4000):
        m = 0
        for n in range(32, table.cap + 1, 32):
            m += rng.binomial(32, s)
            v = table.verdict(n, m)
            if v == "prune":
                break
            if v == ACCEPT:
                accepted += 1
                off += abs(m / n - s) >= 0.05
                break
    assert accepted > 1000 and off / accepted <= 0.03 + 3 * math.sqrt(0.03 / accepted) + 0.02


def test_prune_probability_matches_simulation():
    fewest = min_matches(J, 0.5, 0.03, 32, 128)
    rng = np.random.default_rng(2)
    lost = 0
    for _ in range(4000):
        m = 0
        for low in fewest:
            m += rng.binomial(32, 0.5)
            if m < low:
                lost += 1
                break
    assert lost / 4000 == pytest.approx(prune_probability(0.5, fewest, 32), abs=0.02)
