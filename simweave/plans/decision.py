"""Decision tables: what the posterior says after n hashes of which m agreed, computed once on the driver.

A table has a cell for every multiple n of the step and every m that may go on; Spark plans see it as literals.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np

from simweave.functions.beta import binom_pmf

PRUNE, GO_ON, ACCEPT = "prune", "continue", "accept"


@dataclass(frozen=True)
class JoinParams:
    """Parameters of a verification: threshold, recall level, accuracy, hashes per round and their largest number."""

    t: float
    eps: float = 0.03
    delta: float = 0.05
    gamma: float = 0.03
    step: int = 32
    cap: int | None = None

    def __post_init__(self):
        for name in ("t", "eps", "delta", "gamma"):
            if not 0 < getattr(self, name) < 1:
                raise ValueError(f"{name} must be between 0 and 1")
        if self.step < 1 or (self.cap is not None and self.cap < 1):
            raise ValueError("step and cap must be positive")


def round_up(n: int, step: int) -> int:
    return -(-n // step) * step


def min_matches(posterior, t: float, eps: float, step: int, cap: int) -> list[int]:
    """For n = step, 2 step, ... cap: the fewest matches at which the threshold is still likely enough (n + 1 if none)."""
    out, low = [], 0
    for n in range(step, cap + 1, step):
        lo, hi = low, n + 1
        while lo < hi:
            mid = (lo + hi) // 2
            if posterior.prob_ge(t, mid, n) >= eps:
                hi = mid
            else:
                lo = mid + 1
        low = lo if lo <= n else low
        out.append(lo)
    return out


@dataclass
class DecisionTable:
    """fewest[k] and accepted[k] (inclusive runs of m) after (k + 1) step hashes."""

    params: JoinParams
    posterior: object
    cap: int
    fewest: list[int]
    accepted: list[list[tuple[int, int]]] = field(default_factory=list)

    def verdict(self, n: int, m: int) -> str:
        k = n // self.params.step - 1
        if m < self.fewest[k]:
            return PRUNE
        return ACCEPT if any(a <= m <= b for a, b in self.accepted[k]) else GO_ON

    def rows(self) -> list[tuple[int, int, str, float, float, float]]:
        """(n, m, verdict, estimate, probability, concentration) of every cell that is not pruned."""
        p, q = self.params, self.posterior
        return [
            (n, m, self.verdict(n, m), q.estimate(m, n), q.prob_ge(p.t, m, n), q.concentration(p.delta, m, n))
            for k, n in enumerate(range(p.step, self.cap + 1, p.step)) for m in range(self.fewest[k], n + 1)
        ]


def _accepted(posterior, params: JoinParams, n: int, low: int) -> list[tuple[int, int]]:
    """Runs of m from low to n at which the estimate is accurate enough.

    An estimate is least certain where half of the hashes agree and more certain the farther from there, so each side of the
    middle is one run that a binary search finds.
    """
    good = lambda m: posterior.concentration(params.delta, m, n) >= 1 - params.gamma
    middle = min(max(low, n // 2), n)
    if low > n:
        return []
    below = -1
    if low <= middle and good(low):
        lo, hi = low, middle
        while lo < hi:
            mid = (lo + hi + 1) // 2
            lo, hi = (mid, hi) if good(mid) else (lo, mid - 1)
        below = lo
    lo, hi = max(middle, below + 1), n + 1
    while lo < hi:
        mid = (lo + hi) // 2
        lo, hi = (lo, mid) if good(mid) else (mid + 1, hi)
    runs = ([(low, below)] if below >= 0 else []) + ([(lo, n)] if lo <= n else [])
    return [(low, n)] if len(runs) == 2 and runs[0][1] + 1 == runs[1][0] else runs


@lru_cache(maxsize=256)
def decision_table(posterior, params: JoinParams, estimates: bool = True) -> DecisionTable:
    """The table for params; with estimates, also the runs of m at which the estimate is accurate enough."""
    cap = round_up(params.cap or required_cap(posterior, params), params.step)
    fewest = min_matches(posterior, params.t, params.eps, params.step, cap)
    accepted = [_accepted(posterior, params, n, fewest[k]) if estimates else [] for k, n in enumerate(range(params.step, cap + 1, params.step))]
    return DecisionTable(params, posterior, cap, fewest, accepted)


@lru_cache(maxsize=256)
def required_cap(posterior, params: JoinParams, most: int = 1 << 17) -> int:
    """Smallest multiple of the step from which on every pair that is not pruned is accepted; an error if that is over most."""
    n, quiet, out = params.step, 0, params.step
    while quiet < 8:
        if n > most:
            raise ValueError(f"more than {most} hashes are needed; choose a larger delta or gamma, or give a cap")
        low = min_matches(posterior, params.t, params.eps, n, n)[0]
        # the least certain survivor is the one with a share of matches nearest a half
        worst = min(max(low, n // 2), n)
        near = [m for m in {low, worst, min(n, worst + 1), max(low, worst - 1)} if low <= m <= n]
        if all(posterior.concentration(params.delta, m, n) >= 1 - params.gamma for m in near):
            quiet += 1
        else:
            quiet, out = 0, n + params.step
        n += params.step
    return out


def prune_probability(match: float, fewest: list[int], step: int) -> float:
    """Chance that a pair with this match probability is pruned at one of the rounds (exact recursion over rounds)."""
    ways = np.array([binom_pmf(m, step, match) for m in range(step + 1)])
    alive, lost = np.array([1.0]), 0.0
    for low in fewest:
        alive = np.convolve(alive, ways)
        cut = min(low, len(alive))
        lost += float(alive[:cut].sum())
        alive[:cut] = 0
    return lost


def classical_hashes_needed(s: float, delta: float, gamma: float, rounding: str = "outward", most: int = 2000) -> tuple[int, int]:
    """Hashes at which the match fraction is within delta with probability 1 - gamma: the first non-trivial n, and the n from which on it holds.

    Summation limits are rounded outward (default) or inward. Small n pass the outward test by accident of rounding; n counts as
    non-trivial once the interval is narrower than the estimate's own range, n >= 1 / (2 delta) + 1.
    """
    from math import ceil, floor

    good = []
    for n in range(1, most + 1):
        lo, hi = n * (s - delta), n * (s + delta)
        lo, hi = (floor(lo + 1e-9), ceil(hi - 1e-9)) if rounding == "outward" else (ceil(lo - 1e-9), floor(hi + 1e-9))
        mass = sum(binom_pmf(m, n, s) for m in range(max(lo, 0), min(hi, n) + 1))
        good.append(mass >= 1 - gamma)
    stable = max((n for n, ok in enumerate(good, 1) if not ok), default=0) + 1
    first = next((n for n, ok in enumerate(good, 1) if ok and n >= 1 / (2 * delta) + 1), most)
    return first, stable


def classical_variance(s: float, n: int) -> float:
    """Variance of the match fraction."""
    return s * (1 - s) / n
