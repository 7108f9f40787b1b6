"""Closed forms against each other, series and exact counting."""

import math

import numpy as np
import pytest

from lowbits.functions import theory as t
from lowbits.operators import planner
from lowbits.plans.theory_queries import PRINTED

#: Storage gains of one bit over 32 bits, as published for the ten pairs.
GAINS = [15.5, 16.6, 20.4, 13.3, 12.4, 10.7, 7.3, 4.3, 3.4, 3.1]


def test_printed_gains():
    for (_, r1, r2, R), g in zip(PRINTED, GAINS):
        assert abs(t.storage_gain(R, r1, r2, 32, 1) - g) <= 0.1
        assert abs(t.storage_gain(R, r1, r2, 64, 1) - 2 * t.storage_gain(R, r1, r2, 32, 1)) < 1e-6


def test_headlines():
    assert math.isclose(t.storage_gain(0.5, 1e-12, 1e-12, 64, 1), 64 / 3, rel_tol=1e-6)
    assert math.isclose(t.storage_gain_onebit(1, 1, 64), 64)
    assert math.isclose(t.inflation(0.5, 1e-12, 1e-12, 1), 3, rel_tol=1e-6)
    assert math.isclose(planner.fold_breakeven(), 1 / math.sqrt(3), rel_tol=1e-6)
    assert math.isclose(t.fold_ratio(1 - 1e-9, 1e-12, 1e-12), 2, rel_tol=1e-6)
    assert [planner.best_b(R, 1e-12, 1e-12) for R in (0.1, 0.2, 0.3, 0.4, 0.8)] == [4, 3, 2, 1, 1]
    assert math.isclose(planner.crossover(1, 2, 1e-12), 1 / 3, rel_tol=1e-6)
    assert planner.choose_estimator(0.9, 0.01, 0.01) == "fold" and planner.choose_estimator(0.5, 0.01, 0.01) == "low1"
    assert planner.choose_estimator(0.591, 0.062, 0.061) == "low1" and planner.choose_estimator(0.9, 0.01, 0.01, hash_budget=1) == "low1"
    assert planner.sample_size(1, 0.5, 1e-12, 1e-12, 0.05) == 300


@pytest.mark.parametrize("case", [(20, 4, 4, 2, 1, 0.62241), (20, 10, 5, 3, 2, 0.34283), (100, 20, 15, 10, 1, 0.67157), (100, 60, 20, 15, 3, 0.26453)])
def test_exact_finite_universe(case):
    D, f1, f2, a, b, want = case
    got = t.match_prob_exact(D, f1, f2, a, b)
    assert abs(got - want) < 1e-5
    assert abs(got - t.match_prob_from_counts(f1, f2, a, D, b)) < 0.01 * (20 / D) + 0.002


def test_exact_law_approaches_the_closed_form():
    gaps = [abs(t.match_prob_exact(D, D // 5, D // 5, D // 10, 1) - t.match_prob_from_counts(D // 5, D // 5, D // 10, D, 1)) for D in (20, 40, 80)]
    assert gaps[0] > gaps[1] > gaps[2]
    assert sum(t.minima_pmf_exact(12, 5, 4, 2, i, j) for i in range(12) for j in range(12)) == 1


@pytest.mark.parametrize("b", [1, 2, 3])
def test_three_routes_agree(b):
    for r1, r2, s in ((0.2, 0.1, 0.05), (0.5, 0.5, 0.25), (0.3, 0.25, 0.2)):
        R = s / (r1 + r2 - s)
        law = t.match_prob(R, r1, r2, b)
        assert math.isclose(law, t.match_prob_series(r1, r2, s, b), abs_tol=1e-9)
        assert math.isclose(law, R + t.chance_mass(r1, r2, s, b), abs_tol=1e-9)


def test_residue_limits_and_slopes():
    for b in (1, 2, 4, 8):
        assert math.isclose(t.residue(1e-15, b), 2.0**-b, rel_tol=1e-9) and t.residue(1.0, b) == 0.0
        rs = [t.residue(r, b) for r in np.linspace(0.001, 0.999, 60)]
        assert all(x >= y for x, y in zip(rs, rs[1:])) and rs[0] <= 2.0**-b
        assert t.residue_dr(0.3, b) <= 0
    assert all(t.residue(0.2, b) > t.residue(0.2, b + 1) for b in range(1, 6)) and t.residue(0.2, 32) < 1e-9


def test_variance_limits_and_gains():
    assert math.isclose(t.var_low(0.6, 0.3, 0.2, 40, 10), t.var_full(0.6, 10), rel_tol=1e-6)
    for R in (0.2, 0.5, 0.9):
        for r in (1e-9, 0.3):
            assert math.isclose(t.storage_gain(R, r, r, 32, 2), t.storage_gain_equal(R, r, 32, 2), rel_tol=1e-9)
    assert math.isclose(t.storage_gain(1 - 1e-9, 0.4, 0.4, 32, 2), t.storage_gain_limit(0.4, 32, 2), rel_tol=1e-6)
    assert math.isclose(t.storage_gain(0.5, 0.3, 0.3, 32, 1), t.storage_gain_onebit(0.5, 0.3, 32), rel_tol=1e-6)


def test_fold_inversion_and_its_caveat():
    for R in (0.3, 0.6, 0.95):
        T = t.fold_prob(t.match_prob(R, 0.1, 0.2, 1))
        assert math.isclose(t.r_from_fold(T, 0.1, 0.2), R, abs_tol=1e-9)
    assert t.fold_valid_from(0.5, 0.5) == pytest.approx(0.25)
    assert t.r_from_fold(t.fold_prob(t.match_prob(0.1, 0.5, 0.5, 1)), 0.5, 0.5) != pytest.approx(0.1)
    assert t.var_fold(0.25, 0.5, 0.5, 10) is None or t.var_fold(0.25, 0.5, 0.5, 10) > 1e6
    assert t.joint_size(0.5, 30, 30) == pytest.approx(20) and t.feasible_range(0.9, 0.9)[0] == pytest.approx(0.8)
    assert t.hash_cost(64, True) == 128 and t.storage_bits(2, 100) == 200


def test_column_twins(spark):
    from pyspark.sql import functions as F

    rows = [(R, a, b, n) for R in (0.3, 0.8) for a, b in ((1e-12, 1e-9), (0.2, 0.1), (0.9, 0.9)) for n in (1, 3, 32)]
    df = spark.createDataFrame(rows, "R double, r1 double, r2 double, b int")
    R, r1, r2, b = (F.col(c) for c in df.columns)
    got = df.select("*", t.match_prob(R, r1, r2, b).alias("e"), t.var_low(R, r1, r2, b, 10).alias("v"), t.var_fold(R, r1, r2, F.lit(10)).alias("w"), t.residue(F.lit(1.0), b).alias("one")).collect()
    for x in got:
        assert x.e == pytest.approx(t.match_prob(x.R, x.r1, x.r2, x.b), rel=1e-9)
        assert x.v == pytest.approx(t.var_low(x.R, x.r1, x.r2, x.b, 10), rel=1e-9)
        assert x.w == pytest.approx(t.var_fold(x.R, x.r1, x.r2, 10), rel=1e-9) and x.one == 0


def test_breakeven_in_closed_form():
    for r1, r2 in ((1e-12, 1e-12), (0.1, 0.1), (0.3, 0.2), (0.02, 0.015)):
        assert math.isclose(planner.fold_breakeven_closed(r1, r2), planner.fold_breakeven(r1, r2), rel_tol=1e-6)
