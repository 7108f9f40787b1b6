"""Choosing b, k and the estimator from the closed forms."""

from __future__ import annotations

import math

from ..functions import theory

CANDIDATES = (1, 2, 3, 4, 8, 16, 32)


def best_b(R: float, r1: float, r2: float, candidates=CANDIDATES) -> int:
    """The number of bits with the least storage factor."""
    return min(candidates, key=lambda b: (theory.storage_factor(R, r1, r2, b), b))


def sample_size(b: int, R: float, r1: float, r2: float, target_sd: float) -> int:
    return math.ceil(theory.var_low(R, r1, r2, b, 1) / target_sd**2 - 1e-9)


def _bisect(f, lo: float, hi: float) -> float:
    for _ in range(80):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if f(mid) < 0 else (lo, mid)
    return (lo + hi) / 2


def crossover(b1: int, b2: int, r: float) -> float:
    """Resemblance from which b1 bits need less space than b2 > b1 bits, equal densities."""
    return _bisect(lambda R: theory.storage_factor(R, r, r, b2) - theory.storage_factor(R, r, r, b1), 1e-6, 1 - 1e-9)


def fold_breakeven(r1: float = 1e-12, r2: float = 1e-12) -> float:
    """Resemblance from which the folded bit beats one bit."""
    low = theory.fold_valid_from(r1, r2) + 1e-6
    return _bisect(lambda R: theory.fold_ratio(R, r1, r2) - 1, low, 1 - 1e-9)


def fold_breakeven_closed(r1, r2):
    """The same in closed form, for Columns too: both variances are equal where E (1 - E) = 1 / 6."""
    floor, slope = theory.floor_slope(r1, r2, 1)
    return ((1 + 1 / math.sqrt(3)) / 2 - floor) / slope


def choose_estimator(R: float, r1: float, r2: float, least_gain: float = 1.25, hash_budget: float = 2.0) -> str:
    """'fold' for very high similarity, else 'low<b>'.

    The folded bit needs two permutations per stored bit and its estimate is biased near the break-even, so it is chosen only
    where it saves at least ``least_gain`` of the space and two permutations per sample are within ``hash_budget``."""
    b = best_b(R, r1, r2)
    v = theory.var_fold(R, r1, r2, 1)
    if hash_budget >= theory.hash_cost(1, True) and R > fold_breakeven(r1, r2) and v and theory.storage_factor(R, r1, r2, b) >= least_gain * v:
        return "fold"
    return f"low{b}"
