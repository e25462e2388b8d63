"""Leaf numerics against brute force: the dense posterior, Newton's mode, finite differences, closed forms."""

from __future__ import annotations

import math

import numpy as np
import pytest

from arrayfactor.functions import gp
from arrayfactor.functions.kernels import KINDS, Kernel, covariance
from arrayfactor.functions.normal import cdf, hazard, log_cdf
from arrayfactor.operators.sampling import subarrays_for_coverage
from arrayfactor.plans import cost

RNG = np.random.default_rng(0)
ROWS = [RNG.normal(size=(m, 2)) for m in (4, 5, 3)]
Y = (RNG.random((4, 5, 3)) < 0.4).astype(float)


def dense(spec):
    out = np.ones((1, 1))
    for s in spec.sigma:
        out = np.kron(out, s)
    return out


@pytest.mark.parametrize("x", [-38.0, -20.0, -5.0, -0.3, 0.0, 1.7, 6.0])
def test_normal_tails(x):
    exact = math.log(0.5 * math.erfc(-x / math.sqrt(2)))
    assert log_cdf(np.array([x]))[0] == pytest.approx(exact, rel=1e-9, abs=1e-12)
    density = math.exp(-0.5 * x * x - 0.5 * math.log(2 * math.pi) - exact)
    assert hazard(np.array([x]))[0] == pytest.approx(density, rel=1e-8)
    assert cdf(np.array([x]))[0] == pytest.approx(math.exp(exact), rel=1e-8)


def test_probit_expectation_and_single_cell():
    assert hazard(np.zeros(1))[0] == pytest.approx(math.sqrt(2 / math.pi))
    post = gp.probit(np.ones((1, 1)), gp.Spectrum([np.eye(1), np.eye(1)]), sweeps=200, tol=1e-16)
    assert post.mean[0, 0] == pytest.approx(0.506054, abs=1e-6)


@pytest.mark.parametrize("kind", KINDS)
def test_fixed_point_is_the_posterior_mode(kind):
    post, spec = gp.infer(ROWS, Y, Kernel(kind, scale=1.3, gamma=0.4), sweeps=5000, tol=1e-18)
    lam, s = dense(spec), 2 * Y.ravel() - 1
    m = np.zeros(Y.size)
    for _ in range(50):  # Newton on the log posterior, with its own dense algebra
        h = hazard(s * m)
        w = h * (s * m + h)
        m = lam @ np.linalg.solve(np.eye(len(m)) + w[:, None] * lam, w * m + s * h)
    assert np.abs(post.mean.ravel() - m).max() < 1e-5
    assert all(b >= a - 1e-9 for a, b in zip(post.bound, post.bound[1:]))


@pytest.mark.parametrize("kind", KINDS)
def test_gradient_by_finite_differences(kind):
    kernel = Kernel(kind, scale=1.3, gamma=0.4)
    bound = lambda rows: gp.infer(rows, Y, kernel, sweeps=4000, tol=1e-18)[0].bound[-1]
    post, spec = gp.infer(ROWS, Y, kernel, sweeps=4000, tol=1e-18)
    grads = gp.factor_gradients(ROWS, post, spec, kernel)
    for k, i, d in ((0, 1, 0), (1, 2, 1), (2, 0, 0)):
        up, down = [r.copy() for r in ROWS], [r.copy() for r in ROWS]
        up[k][i, d] += 1e-5
        down[k][i, d] -= 1e-5
        assert grads[k][i, d] == pytest.approx((bound(up) - bound(down)) / 2e-5, rel=1e-3, abs=1e-5)


def test_gaussian_equals_dense_and_variances():
    y = RNG.normal(size=Y.shape)
    post, spec = gp.infer(ROWS, y, Kernel(), "continuous", noise=0.7)
    lam = dense(spec)
    full = lam + 0.7 * np.eye(len(lam))
    assert np.allclose(post.mean.ravel(), lam @ np.linalg.solve(full, y.ravel()))
    assert post.bound[0] == pytest.approx(-0.5 * y.ravel() @ np.linalg.solve(full, y.ravel()) - 0.5 * np.linalg.slogdet(full)[1] - 0.5 * y.size * math.log(2 * math.pi))
    assert np.allclose(spec.variance().ravel(), np.diag(lam @ np.linalg.inv(np.eye(len(lam)) + lam)))


def test_prediction_inside_the_bag_is_the_posterior_mean():
    kernel = Kernel(nugget=1e-10)
    post, spec = gp.infer(ROWS, Y, kernel, sweeps=3000, tol=1e-18)
    at = [(0, 1, 2), (3, 4, 0)]
    mean, var = gp.predictive([np.array([ROWS[k][c[k]] for c in at]) for k in range(3)], ROWS, post, spec, kernel)
    assert np.allclose(mean, [post.mean[c] for c in at], atol=1e-6)
    assert np.allclose(var, [spec.variance()[c] for c in at], atol=1e-6)


def test_masked_cells_carry_no_evidence():
    mask = np.ones(Y.shape, bool)
    mask[1, 1, 1] = False
    flipped = Y.copy()
    flipped[1, 1, 1] = 1 - flipped[1, 1, 1]
    a = gp.infer(ROWS, Y, Kernel(), sweeps=50, mask=mask)[0].mean
    b = gp.infer(ROWS, flipped, Kernel(), sweeps=50, mask=mask)[0].mean
    assert np.allclose(a, b)


def test_linear_kernel_is_a_ridge_tucker_model():
    y = RNG.normal(size=Y.shape)
    post, _ = gp.infer(ROWS, y, Kernel("linear", offset=0.0, nugget=0.0), "continuous", noise=1.0)
    design = np.kron(np.kron(ROWS[0], ROWS[1]), ROWS[2])
    core = np.linalg.solve(design.T @ design + np.eye(design.shape[1]), design.T @ y.ravel())
    assert np.allclose(post.mean.ravel(), design @ core, atol=1e-8)


def test_relabelling_leaves_the_bound():
    order = [RNG.permutation(len(r)) for r in ROWS]
    moved = gp.infer([r[o] for r, o in zip(ROWS, order)], Y[np.ix_(*order)], Kernel(), sweeps=20)[0].bound[-1]
    assert moved == pytest.approx(gp.infer(ROWS, Y, Kernel(), sweeps=20)[0].bound[-1])


def test_lazy_pull_equals_step_by_step():
    lazy = gp.ShardState(lambda m, i: np.zeros(1), 20, 0.1, 1.0)
    lazy.deviation[0, 1], lazy.seen[0, 1], lazy.now = np.array([0.7]), 0, 7
    assert lazy.settled((0, 1))[0] == pytest.approx(0.675864, abs=1e-6)


def test_count_likelihood_and_costs():
    assert gp.infer(ROWS, np.round(3 * RNG.random(Y.shape)), Kernel(), "count")[0].mean.shape == Y.shape
    assert subarrays_for_coverage([80] * 3, 68.852e9) == 134_477
    assert 50**3 * 590_400 / (20_000 * 12_295 * 280) == pytest.approx(1.0719, abs=1e-4)
    assert cost.local_time([50] * 3, 100, 4) == pytest.approx(25 * (3 * 50**3 + 3 * 50 * 50**3))


def test_kernels_are_positive():
    for kind in KINDS:
        assert np.linalg.eigvalsh(covariance(ROWS[1], ROWS[1], Kernel(kind, gamma=0.4), same=True)).min() > -1e-9
