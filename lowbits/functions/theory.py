"""Closed forms: match law, variances, storage trade-offs.

Every formula takes Columns or Python numbers and answers in kind.  Densities r = f / D belong to the range of the
permuted values: with 64-bit hashes r is about 0, with a permutation of D ids it is f / D.  Small densities go
through log1p / expm1.  r = 0 (empty set) has no resemblance: residue is its limit there.
"""

from __future__ import annotations

import math
from fractions import Fraction
from math import comb

from pyspark.sql import Column
from pyspark.sql import functions as F


class _Numbers:
    """Python twins of the column functions used below; None is null."""

    exp, log, log1p, expm1 = staticmethod(math.exp), staticmethod(math.log), staticmethod(math.log1p), staticmethod(math.expm1)
    sqrt = staticmethod(math.sqrt)
    pow = staticmethod(lambda a, b: float(a) ** b)
    greatest = staticmethod(max)


class _Columns:
    exp, log, log1p, expm1, sqrt, pow = F.exp, F.log, F.log1p, F.expm1, F.sqrt, F.pow
    greatest = staticmethod(lambda a, b: F.greatest(*(x if isinstance(x, Column) else F.lit(x) for x in (a, b))))


def _ops(*xs):
    return _Columns if any(isinstance(x, Column) for x in xs) else _Numbers


def _col(x) -> Column:
    return x if isinstance(x, Column) else F.lit(float(x))


def residue(r, b):
    """Chance-agreement constant of one set: r (1-r)^(2^b - 1) / (1 - (1-r)^(2^b)); 2^-b as r tends to 0, 0 at r = 1."""
    m = _ops(r, b)
    if m is _Numbers:
        if r >= 1:
            return 0.0
        if r < 1e-300:
            return 2.0**-b
        n = 2.0**b
        return math.exp(math.log(r) + (n - 1) * math.log1p(-r)) / -math.expm1(n * math.log1p(-r))
    r, n = _col(r), F.pow(F.lit(2.0), _col(b))
    inner = F.exp(F.log(r) + (n - 1) * F.log1p(-r)) / -F.expm1(n * F.log1p(-r))
    return F.when(r >= 1, F.lit(0.0)).when(r < 1e-300, 1 / n).otherwise(inner)


def residue_dr(r, b, h: float = 1e-6):
    """Slope of the residue in r, by central differences; never positive."""
    return (residue(r + h, b) - residue(r - h, b)) / (2 * h)


def floor_slope(r1, r2, b):
    """(floor, slope) of the match law; each set's residue is weighted by the other's share in the floor, by its own in the slope."""
    q1, q2 = residue(r1, b), residue(r2, b)
    s1 = r1 / (r1 + r2)
    s2 = r2 / (r1 + r2)
    return q1 * s2 + q2 * s1, 1 - (q1 * s1 + q2 * s2)


def match_prob(R, r1, r2, b):
    """Probability that the lowest b bits of two minima agree."""
    floor, slope = floor_slope(r1, r2, b)
    return floor + slope * R


def match_prob_from_counts(f1, f2, a, D, b):
    """The same law from set sizes and intersection size."""
    return match_prob(a / (f1 + f2 - a), f1 / D, f2 / D, b)


def chance_mass(r1, r2, s, b):
    """Probability that the low bits agree although the minima differ; s = a / D."""
    q1, q2, u = residue(r1, b), residue(r2, b), r1 + r2 - s
    return q1 * (r2 - s) / u + q2 * (r1 - s) / u


def minima_pmf(i, j, r1, r2, s):
    """Joint probability of minima i and j for a large universe."""
    m = _ops(i, j, r1, r2, s)
    if m is _Numbers:
        if i == j:
            return s * (1 - r1 - r2 + s) ** i
        lo, hi, own, other = (i, j, r1, r2) if i < j else (j, i, r2, r1)
        return other * (own - s) * (1 - other) ** (hi - lo - 1) * (1 - r1 - r2 + s) ** lo
    i, j, r1, r2, s = map(_col, (i, j, r1, r2, s))
    joint = 1 - r1 - r2 + s
    less = r2 * (r1 - s) * F.pow(1 - r2, j - i - 1) * F.pow(joint, i)
    more = r1 * (r2 - s) * F.pow(1 - r1, i - j - 1) * F.pow(joint, j)
    return F.when(i == j, s * F.pow(joint, i)).when(i < j, less).otherwise(more)


def match_prob_series(r1, r2, s, b, terms: int = 4000) -> float:
    """The match law as a truncated sum over the joint probabilities, independent of the closed form."""
    n, total, joint = 2**b, 0.0, 1 - r1 - r2 + s
    total += s * (1 - joint**terms) / (1 - joint)
    for own, other in ((r1, r2), (r2, r1)):
        for d in range(n, terms, n):
            w = other * (own - s) * (1 - other) ** (d - 1)
            if w < 1e-18:
                break
            total += w * (1 - joint ** (terms - d)) / (1 - joint)
    return total


def minima_pmf_exact(D: int, f1: int, f2: int, a: int, i: int, j: int) -> Fraction:
    """Joint probability of minima i and j for a random permutation of 0..D-1, by counting."""

    def place(n: int, k: int) -> int:
        return comb(n, k) if 0 <= k <= n else 0

    only1, only2 = f1 - a, f2 - a
    total = comb(D, a) * comb(D - a, only1) * comb(D - f1, only2)
    if i == j:
        ways = place(D - i - 1, a - 1) * place(D - i - a, only1) * place(D - i - a - only1, only2) if a else 0
        return Fraction(ways, total)
    lo, hi, first, second = (i, j, only1, only2) if i < j else (j, i, only2, only1)
    # value lo belongs to the first set only, hi is the second set's least: shared or not
    ways = 0
    if first:
        free = D - hi - 1
        if a:  # hi is shared
            ways += place(free, a - 1) * place(free - (a - 1), second) * place(D - lo - 1 - a - second, first - 1)
        if second:
            ways += place(free, second - 1) * place(free - (second - 1), a) * place(D - lo - 1 - a - second, first - 1)
    return Fraction(ways, total)


def match_prob_exact(D: int, f1: int, f2: int, a: int, b: int) -> float:
    """The match probability of a finite universe, summed over all pairs of minima."""
    n = 2**b
    return float(sum(minima_pmf_exact(D, f1, f2, a, i, j) for i in range(D) for j in range(i % n, D, n)))


def joint_size(R, f1, f2):
    """Intersection size from resemblance: R / (1 + R) (f1 + f2)."""
    return R / (1 + R) * (f1 + f2)


def feasible_range(r1, r2):
    """(least, greatest) resemblance that densities r1 and r2 allow."""
    return max(0.0, r1 + r2 - 1) / min(1.0, r1 + r2), min(r1, r2) / max(r1, r2)


def var_full(R, k):
    return R * (1 - R) / k


def var_low(R, r1, r2, b, k):
    floor, slope = floor_slope(r1, r2, b)
    e = floor + slope * R
    return e * (1 - e) / (k * slope * slope)


def fold_prob(e1, m: int = 2):
    """Agreement of bits folded from m permutations when single low bits agree with probability e1."""
    if m == 2:
        return e1 * e1 + (1 - e1) * (1 - e1)
    return (1 + _ops(e1).pow(2 * e1 - 1, m)) / 2


def r_from_fold(t, r1, r2, m: int = 2):
    """Resemblance from the folded agreement of m permutations; the positive root, so valid from fold_valid_from on."""
    o = _ops(t, r1, r2)
    floor, slope = floor_slope(r1, r2, 1)
    inner = o.greatest(2 * t - 1, 0.0)
    root = o.sqrt(inner) if m == 2 else o.pow(inner, 1 / m)
    return (root + 1 - 2 * floor) / (2 * slope)


def fold_valid_from(r1: float, r2: float) -> float:
    floor, slope = floor_slope(r1, r2, 1)
    return max(0.0, (0.5 - floor) / slope)


def var_fold(R, r1, r2, k, m: int = 2):
    """First-order variance of the estimator folded from m permutations; null (None) where 2T <= 1."""
    o = _ops(R, r1, r2, k)
    _, slope = floor_slope(r1, r2, 1)
    t = fold_prob(match_prob(R, r1, r2, 1), m)
    if o is _Numbers:
        return t * (1 - t) / (m * m * k * slope * slope * (2 * t - 1) ** (2 - 2 / m)) if 2 * t > 1 else None
    return F.when(2 * t > 1, t * (1 - t) / (m * m * k * slope * slope * F.pow(2 * t - 1, F.lit(2 - 2 / m))))


def fold_ratio(R, r1, r2):
    """Variance of one bit over variance of the folded bit at equal stored bits."""
    return var_low(R, r1, r2, 1, 1) / var_fold(R, r1, r2, 1)


def storage_bits(b, k):
    return b * k


def hash_cost(k, folded: bool = False, m: int = 2):
    """Permutations to apply for k stored samples, each folded from m."""
    return m * k if folded else k


def words_compared(b, k):
    """64-bit words that one pair costs: b planes of k bits on each side."""
    return b * math.ceil(k / 64)


def storage_factor(R, r1, r2, b):
    """Bits per sample times variance per sample: lower is better."""
    return b * var_low(R, r1, r2, b, 1)


def storage_factor_fold(R, r1, r2):
    return var_fold(R, r1, r2, 1)


def storage_gain(R, r1, r2, b1, b2):
    """How many times less space b2 bits need than b1 bits, at equal variance."""
    return storage_factor(R, r1, r2, b1) / storage_factor(R, r1, r2, b2)


def storage_gain_equal(R, r, b1, b2):
    """The gain for equal densities, written out: residues stand for floors, and slope is 1 - residue."""
    q1, q2 = residue(r, b1), residue(r, b2)
    e1, e2 = q1 + (1 - q1) * R, q2 + (1 - q2) * R
    return (b1 * e1 * (1 - q2)) / (b2 * e2 * (1 - q1))


def storage_gain_limit(r, b1, b2):
    """The gain as R tends to 1, equal densities."""
    return b1 / b2 * (1 - residue(r, b2)) / (1 - residue(r, b1))


def storage_gain_onebit(R, r, b1):
    """The gain of one bit over b1 >= 32 bits, equal densities."""
    return b1 * R / (R + 1 - r)


def inflation(R, r1, r2, b):
    """Samples needed with b bits over samples needed in full, at equal variance."""
    return var_low(R, r1, r2, b, 1) / var_full(R, 1)
