"""Binomial likelihood and the regularised incomplete beta function, in logs where tails are small."""

from __future__ import annotations

from math import exp, inf, lgamma, log, log1p


def log_beta(a: float, b: float) -> float:
    return lgamma(a) + lgamma(b) - lgamma(a + b)


def binom_pmf(m: int, n: int, s: float) -> float:
    """Probability of m matches among n hashes at match probability s."""
    if s <= 0 or s >= 1:
        return float(m == (0 if s <= 0 else n))
    return exp(lgamma(n + 1) - lgamma(m + 1) - lgamma(n - m + 1) + m * log(s) + (n - m) * log1p(-s))


def _fraction(x: float, a: float, b: float) -> float:
    """Continued fraction of the incomplete beta function, evaluated front to back."""
    tiny = 1e-300
    c, d = 1.0, 1.0 - (a + b) * x / (a + 1)
    d = 1.0 / (d if abs(d) > tiny else tiny)
    out = d
    for k in range(1, 10_000):
        for top in (k * (b - k) * x / ((a + 2 * k - 1) * (a + 2 * k)), -(a + k) * (a + b + k) * x / ((a + 2 * k) * (a + 2 * k + 1))):
            d = 1.0 + top * d
            d = 1.0 / (d if abs(d) > tiny else tiny)
            c = 1.0 + top / c
            c = c if abs(c) > tiny else tiny
            out *= c * d
        if abs(c * d - 1.0) < 1e-15:
            break
    return out


def log_inc_beta(x: float, a: float, b: float) -> float:
    """Log of the lower regularised incomplete beta function; -inf at 0."""
    if x <= 0:
        return -inf
    if x >= 1:
        return 0.0
    front = a * log(x) + b * log1p(-x) - log_beta(a, b)
    if x <= (a + 1) / (a + b + 2):
        return min(0.0, front + log(_fraction(x, a, b)) - log(a))
    upper = front + log(_fraction(1 - x, b, a)) - log(b)
    return log1p(-exp(upper)) if upper < -1e-17 else -inf


def log_inc_beta_tail(x: float, a: float, b: float) -> float:
    """Log of the upper tail, accurate when it is tiny."""
    return log_inc_beta(1 - x, b, a) if x > 0 else 0.0


def reg_inc_beta(x: float, a: float, b: float) -> float:
    """Regularised incomplete beta function."""
    return exp(log_inc_beta(x, a, b)) if x > 0 else 0.0
