"""Solvers, sizes, roundings and factors on small arrays."""

import math

import numpy as np
import pytest

from tallquant.functions.loss import skew_ratio
from tallquant.operators import linalg, sizing, solvers


def problem(n, p, seed=0):
    rng = np.random.default_rng(seed)
    x = np.column_stack([np.ones(n), rng.normal(size=(n, p - 1))])
    return x, x @ rng.normal(size=p) + rng.laplace(size=n), rng.uniform(0.5, 3, n)


@pytest.mark.parametrize("tau", [0.05, 0.25, 0.5, 0.75, 0.95, 0.999])
def test_interior_point_equals_enumeration(tau):
    x, b, w = problem(30, 2)
    exact = solvers.enumerate_exact(x, b, tau, w)
    fit = solvers.interior_point(x, b, tau, w)
    assert fit.objective == pytest.approx(exact.objective, rel=1e-9)
    assert solvers.simplex(x, b, tau, w).objective == pytest.approx(exact.objective, rel=1e-9)


@pytest.mark.parametrize("p, tau", [(3, 0.5), (6, 0.75), (11, 0.9)])
def test_interior_point_is_certified(p, tau):
    x, b, w = problem(3000, p, 1)
    fit = solvers.interior_point(x, b, tau, w)
    assert fit.optimal
    assert np.sum(np.abs(b - x @ fit.beta) < 1e-9) >= p
    assert fit.objective <= solvers.loss(x, b, w, tau, fit.beta + 1e-3) + 1e-9


def test_reflection_gives_the_same_coefficients():
    x, b, w = problem(400, 3, 2)
    a, m = solvers.interior_point(x, b, 0.25, w), solvers.interior_point(-x, -b, 0.75, w)
    assert a.beta == pytest.approx(m.beta, abs=1e-8)


def test_scaling_and_shifting():
    x, b, w = problem(500, 3, 3)
    base = solvers.interior_point(x, b, 0.75, w)
    assert solvers.interior_point(x, 3 * b, 0.75, w).beta == pytest.approx(3 * base.beta, abs=1e-7)
    gamma = np.array([1.0, -2.0, 0.5])
    assert solvers.interior_point(x, b + x @ gamma, 0.75, w).beta == pytest.approx(base.beta + gamma, abs=1e-7)


def test_stacking_keeps_coefficients():
    x, b, w = problem(300, 3, 4)
    one, many = solvers.interior_point(x, b, 0.75, w), solvers.interior_point(np.vstack([x] * 4), np.tile(b, 4), 0.75, np.tile(w, 4))
    assert many.objective == pytest.approx(4 * one.objective, rel=1e-9)
    assert many.beta == pytest.approx(one.beta, abs=1e-6)


def test_degenerate_inputs():
    one = np.ones((1, 1))
    assert solvers.solve_weighted(one, np.array([5.0]), np.ones(1), 0.5).beta[0] == 5
    assert np.isnan(solvers.solve_weighted(np.zeros((0, 2)), np.zeros(0), np.zeros(0), 0.5).beta).all()
    twice = np.column_stack([np.ones(50), np.ones(50), np.arange(50.0)])
    fit = solvers.solve_weighted(twice, np.arange(50.0) * 2 + 1, np.ones(50), 0.5)
    assert np.isnan(fit.beta[1]) and fit.beta[[0, 2]] == pytest.approx([1, 2], abs=1e-8)
    missing = np.array([[1.0, 0.0], [2.0, 0.0], [1.0, 0.0]])
    assert np.isnan(solvers.solve_weighted(missing, np.array([1.0, 4.0, 3.0]), np.ones(3), 0.5).beta[1])


def test_weighted_quantile_hand_value():
    assert solvers.weighted_quantile(np.array([1.0, 2.0, 3.0]), np.array([1.0, 1.0, 3.0]), 0.5) == 3


def test_negative_single_entries():
    x, b = np.array([[1.0], [-2.0], [3.0], [-1.0]]), np.array([2.0, 1.0, -1.0, 4.0])
    fit, exact = solvers.solve_weighted(x, b, np.ones(4), 0.7), solvers.enumerate_exact(x, b, 0.7)
    assert fit.objective == pytest.approx(exact.objective)


def test_sizes():
    assert sizing.size_quantile(864, 12, 0.1, 0.75, 0.05, True) == pytest.approx(1.68e9, rel=0.01)
    assert [sizing.estimator_width(n) for n in (6_000, 60_000, 600_000, 10**6, 10**9, 10**12)] == [186, 221, 255, 263, 367, 470]
    assert sizing.kappa_bound("round_fast", 12, 10**6) == 288 and sizing.kappa_bound("sparse_qr_round", 12, 10**6) == 864
    assert sizing.norms_choice(50, 10**6) == "exact" and sizing.norms_choice(400, 10**6) == "median"
    assert sizing.guarantee(0.1) == pytest.approx(11 / 9) and skew_ratio(0.25) == 3
    assert not sizing.fits_memory(1e6, 100)


def test_positive_r():
    assert linalg.positive_r(np.array([[3.0], [4.0]])) == pytest.approx(np.array([[5.0]]))
    a = np.random.default_rng(0).standard_cauchy((300, 5))
    r, s = linalg.positive_r(a), linalg.svd_r(a)
    assert r.T @ r == pytest.approx(a.T @ a, rel=1e-9) and s.T @ s == pytest.approx(a.T @ a, rel=1e-6)
    assert (np.diag(r) > 0).all()
    both = linalg.positive_r(np.vstack([linalg.positive_r(a[:100]), linalg.positive_r(a[100:])]))
    assert both == pytest.approx(r, rel=1e-9)


@pytest.mark.parametrize("d", [1, 2, 5, 8])
def test_roundings_bound_the_sandwich(d):
    a = np.random.default_rng(d).standard_t(2, (2000, d))
    r0 = linalg.positive_r(a)
    slab, _ = linalg.round_slab(lambda rinv: linalg.local_slab_stats(a, rinv), r0)
    low, high = linalg.sandwich(a, slab)
    assert high / low <= 2 * d + 1e-9
    density, _ = linalg.round_density(linalg.local_density_gram(a), r0.T @ r0 / math.sqrt(d))
    low, high = linalg.sandwich(a, density)
    assert high / low <= math.sqrt(d) * 1.001
