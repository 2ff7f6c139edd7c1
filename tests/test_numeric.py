"""Closed forms of the kernels."""

import math

import numpy as np
import pytest

from slotlens.functions import gamma
from slotlens.operators import smoother, spectrum


@pytest.mark.parametrize("q", [0.001, 0.025, 0.5, 0.975, 0.999])
def test_gamma_of_shape_one_is_exponential(q):
    assert gamma.quantile(q, 1.0, 3.0) == pytest.approx(-3 * math.log(1 - q), rel=1e-9)


@pytest.mark.parametrize(("shape", "q"), [(0.3, 0.2), (2.5, 0.975), (400.0, 0.025), (9000.0, 0.5)])
def test_gamma_quantile_inverts_the_cdf(shape, q):
    assert gamma.cdf(gamma.quantile(q, shape, 0.7), shape, 0.7) == pytest.approx(q, abs=1e-9)


def test_gamma_matches_a_chi_square_table():
    # chi-square with 4 degrees of freedom has its 0.95 quantile at 9.4877.
    assert gamma.quantile(0.95, 2.0, 2.0) == pytest.approx(9.4877, abs=1e-4)


def test_degenerate_gamma_has_no_quantile():
    assert math.isnan(gamma.quantile(0.5, 0.0, 1.0))


def test_banded_solve_equals_dense():
    rng = np.random.default_rng(3)
    a = rng.standard_normal((12, 12))
    m = np.array([[(a @ a.T)[i, j] if abs(i - j) <= 3 else 0 for j in range(12)] for i in range(12)]) + 30 * np.eye(12)
    band = np.zeros((4, 12))
    for k in range(4):
        band[k, : 12 - k] = np.diag(m, k)
    b = rng.standard_normal(12)
    assert smoother.solve_banded(band, b) == pytest.approx(np.linalg.solve(m, b))


def test_basis_sums_to_one():
    x = smoother.design(np.arange(100.0), 99.0, 17)
    assert x.sum(axis=1) == pytest.approx(1.0)


@pytest.mark.parametrize("period", [6, 12, 24])
def test_planted_period_is_found(period):
    t = np.arange(720)
    y = np.sin(2 * np.pi * t / period) + np.random.default_rng(1).normal(0, 0.2, 720)
    assert spectrum.pick_period(np.abs(np.fft.rfft(y - y.mean())) ** 2, 720, True) == period


def test_noise_has_no_period():
    y = np.random.default_rng(2).normal(size=720)
    assert spectrum.pick_period(np.abs(np.fft.rfft(y)) ** 2, 720, True) is None


@pytest.mark.parametrize(
    ("p", "r", "f"), [(0.8857, 0.775, 0.8267), (0.9375, 0.75, 0.8333), (0.9118, 0.775, 0.8378), (0.708, 0.6452, 0.6751), (0.3378, 0.362, 0.3495)]
)
def test_published_f_measures_recompute(p, r, f):
    assert 2 * p * r / (p + r) == pytest.approx(f, abs=1e-4)
