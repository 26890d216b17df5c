"""Posteriors of a pair's match probability after m of n hashes agreed, and priors fitted to a sample."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from math import acos, cos, exp, inf, log1p, pi

import numpy as np

from simweave.functions.beta import log_inc_beta, log_inc_beta_tail


def angular_to_cosine(r: float) -> float:
    """Cosine of a pair whose sign bits agree with probability r."""
    return cos(pi * (1 - min(max(r, 0.0), 1.0)))


def cosine_to_angular(c: float) -> float:
    return 1 - acos(min(max(c, -1.0), 1.0)) / pi


def _between(lo: float, hi: float, a: float, b: float) -> float:
    """Log mass of Beta(a, b) in [lo, hi], from the tail that loses fewer digits."""
    if hi <= lo:
        return -inf
    upper = lo > a / (a + b)
    far, near = (log_inc_beta_tail(lo, a, b), log_inc_beta_tail(hi, a, b)) if upper else (log_inc_beta(hi, a, b), log_inc_beta(lo, a, b))
    if near == -inf:
        return far
    return far + log1p(-exp(near - far)) if near < far else -inf


@dataclass(frozen=True)
class BetaPosterior:
    """Jaccard similarity under a Beta(alpha, beta) prior."""

    alpha: float = 1.0
    beta: float = 1.0
    measure: str = "jaccard"

    def prob_ge(self, t: float, m: int, n: int) -> float:
        return exp(log_inc_beta_tail(t, m + self.alpha, n - m + self.beta))

    def mode(self, m: int, n: int) -> float:
        a, b = m + self.alpha, n - m + self.beta
        if a <= 1 or b <= 1:
            return 0.5 if a == b == 1 else float(a > b)
        return (a - 1) / (a + b - 2)

    def estimate(self, m: int, n: int) -> float:
        return self.mode(m, n)

    def concentration(self, delta: float, m: int, n: int) -> float:
        e = self.mode(m, n)
        return exp(_between(max(e - delta, 0.0), min(e + delta, 1.0), m + self.alpha, n - m + self.beta))

    def match_threshold(self, t: float) -> float:
        return t


@dataclass(frozen=True)
class TruncatedPosterior:
    """Cosine through the angular similarity r, with a flat prior of r on [low, high]."""

    low: float = 0.5
    high: float = 1.0
    measure: str = "cosine"

    def _log_mass(self, lo: float, hi: float, m: int, n: int) -> float:
        return _between(max(lo, self.low), min(hi, self.high), m + 1, n - m + 1)

    def prob_ge(self, t: float, m: int, n: int) -> float:
        whole = self._log_mass(self.low, self.high, m, n)
        part = self._log_mass(cosine_to_angular(t), self.high, m, n)
        return exp(part - whole) if part > -inf and whole > -inf else 0.0

    def mode(self, m: int, n: int) -> float:
        return min(max(m / n, self.low), self.high)

    def estimate(self, m: int, n: int) -> float:
        return angular_to_cosine(self.mode(m, n))

    def concentration(self, delta: float, m: int, n: int) -> float:
        e = self.estimate(m, n)
        lo, hi = cosine_to_angular(max(e - delta, angular_to_cosine(self.low))), cosine_to_angular(min(e + delta, 1.0))
        whole, part = self._log_mass(self.low, self.high, m, n), self._log_mass(lo, hi, m, n)
        return exp(part - whole) if part > -inf else 0.0

    def match_threshold(self, t: float) -> float:
        return cosine_to_angular(t)


class GridPosterior:
    """Any prior density on [low, high], by weights on an even grid of mid-points."""

    def __init__(self, density: Callable[[np.ndarray], np.ndarray], low: float, high: float, points: int = 4000, measure: str = "jaccard"):
        step = (high - low) / points
        self.s, self.measure = low + step * (np.arange(points) + 0.5), measure
        with np.errstate(divide="ignore"):
            self.log_prior = np.log(density(self.s))

    def weights(self, m: int, n: int) -> np.ndarray:
        w = self.log_prior + m * np.log(self.s) + (n - m) * np.log1p(-self.s)
        w = np.exp(w - w.max())
        return w / w.sum()

    def _sim(self) -> np.ndarray:
        return np.cos(np.pi * (1 - self.s)) if self.measure == "cosine" else self.s

    def prob_ge(self, t: float, m: int, n: int) -> float:
        return float(self.weights(m, n)[self._sim() >= t].sum())

    def mode(self, m: int, n: int) -> float:
        return float(self.s[self.weights(m, n).argmax()])

    def estimate(self, m: int, n: int) -> float:
        return angular_to_cosine(self.mode(m, n)) if self.measure == "cosine" else self.mode(m, n)

    def concentration(self, delta: float, m: int, n: int) -> float:
        return float(self.weights(m, n)[np.abs(self._sim() - self.estimate(m, n)) < delta].sum())

    def match_threshold(self, t: float) -> float:
        return cosine_to_angular(t) if self.measure == "cosine" else t


class ShiftedBetaPosterior(GridPosterior):
    """Cosine with a Beta(alpha, beta) prior of r stretched over (0.5, 1); not conjugate, so on a grid."""

    def __init__(self, alpha: float, beta: float, points: int = 4000):
        super().__init__(lambda r: (2 * r - 1) ** (alpha - 1) * (2 - 2 * r) ** (beta - 1), 0.5, 1.0, points, "cosine")


def beta_from_moments(mean: float | None, variance: float | None) -> tuple[float, float]:
    """Beta parameters with a sample's mean and population variance; flat where they do not determine one."""
    if mean is None or not variance or variance >= mean * (1 - mean):
        return 1.0, 1.0
    k = mean * (1 - mean) / variance - 1
    return mean * k, (1 - mean) * k


