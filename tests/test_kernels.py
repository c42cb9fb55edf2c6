"""Numpy kernels against closed forms, brute force and each other."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from fieldpress.functions import basis as B
from fieldpress.functions import mixers as M
from fieldpress.functions import sparse as S
from fieldpress.schema import legendre, multiwavelet, piecewise


@pytest.mark.parametrize("spec", [legendre(0), legendre(9), multiwavelet(3, 0), multiwavelet(3, 2), multiwavelet(2, 5), multiwavelet(5, 3, levels_inclusive=True), piecewise(3, 3)])
def test_bases_are_orthonormal(spec):
    assert np.abs(B.gram(spec) - np.eye(spec.size)).max() < 1e-10


def test_published_space_has_256_functions():
    assert multiwavelet(5, 3, levels_inclusive=True).size == 256 and multiwavelet(5, 3).size == 128


def test_multiwavelets_span_the_piecewise_polynomials():
    x = np.linspace(0, 1, 300)
    a, b = B.evaluate_matrix(x, multiwavelet(3, 2)), B.evaluate_matrix(x, piecewise(3, 2))
    assert np.abs(a - b @ np.linalg.lstsq(b, a, rcond=None)[0]).max() < 1e-11


def test_mother_wavelets_have_vanishing_moments():
    g, w = np.polynomial.legendre.leggauss(12)
    x = np.concatenate([(g + 1) / 4, (g + 1) / 4 + 0.5])
    w = np.concatenate([w, w]) / 4
    for p in (0, 1, 3):
        psi = B._halves(x, p) @ B.mother_wavelets(p)
        for j in range(p + 1):
            for m in range(p + 1 + j):
                assert abs((w * x**m) @ psi[:, j]) < 1e-12


def test_haar_sign_and_right_end():
    phi = B.evaluate_matrix(np.array([0.0, 0.49, 0.5, 1.0]), multiwavelet(1, 0))
    assert phi[:, 1].tolist() == pytest.approx([1, 1, -1, -1])


def test_means_are_integrals():
    for spec in (legendre(5), multiwavelet(2, 1)):
        x = np.linspace(0.2, 0.7, 20001)
        assert np.abs(B.evaluate_matrix(x, spec).mean(axis=0) - B.means(spec, 0.2, 0.7)).max() < 2e-3
        assert np.allclose(B.means(spec, 0.3, 0.3), B.evaluate_matrix(np.array([0.3]), spec)[0])


@settings(max_examples=25, deadline=None)
@given(st.integers(0, 10_000), st.integers(8, 30), st.integers(2, 40))
def test_path_is_optimal(seed, rows, cols):
    rng = np.random.default_rng(seed)
    phi, z = rng.normal(size=(rows, cols)), rng.normal(size=rows)
    path = S.lars_lasso_path(phi, z)
    for k in path:
        g = 2 * phi.T @ (z - phi @ k.coef)
        on = k.coef != 0
        assert np.abs(g).max() <= k.lam + 1e-7 and np.allclose(g[on], k.lam * np.sign(k.coef[on]), atol=1e-7)


def test_path_drops_columns():
    """A correlated design in which a column has to leave again."""
    rng = np.random.default_rng(3)
    base = rng.normal(size=(40, 3))
    phi = np.column_stack([base, base @ rng.normal(size=(3, 9)) + 0.1 * rng.normal(size=(40, 9))])
    dropped = False
    for s in range(40):
        z = np.random.default_rng(s).normal(size=40)
        path = S.lars_lasso_path(phi, z)
        dropped |= any(set(a.active) - set(b.active) for a, b in zip(path, path[1:]))
        lam = path[len(path) // 2].lam
        assert np.abs(S.lasso(phi, z, lam) - S.lasso_cd(phi, z, lam, 50_000)).max() < 1e-5
    assert dropped


def test_edge_designs():
    phi = np.zeros((6, 3))
    assert S.fit_lars_loo(phi, np.arange(6.0)).nnz == 0
    phi = np.ones((6, 2))  # twice the same column
    fit = S.fit_lars_loo(phi, np.full(6, 2.0))
    assert np.allclose(phi @ fit.coef, 2.0)
    assert S.fit_lars_loo(np.eye(3), np.zeros(3)).nnz == 0
    path = S.lars_lasso_path(np.eye(3), np.array([3.0, 2.0, 1.0]))
    assert np.allclose(S.coef_at(path, 100.0), 0) and np.allclose(S.coef_at(path, 2.0), [2, 1, 0])


def test_loo_by_updates_is_brute_force():
    rng = np.random.default_rng(0)
    phi, z = rng.normal(size=(30, 12)), rng.normal(size=30)
    errors: list[float] = []
    path = S.lars_lasso_path(phi, z, None, errors)
    for k, e in list(zip(path, errors))[1:]:
        assert e == pytest.approx(S.loo_bruteforce(phi[:, list(k.active)], z), rel=1e-8)


def test_lasso_between_constraints():
    rng = np.random.default_rng(1)
    phi, z = rng.normal(size=(30, 8)), rng.normal(size=30)
    c = S.l1_ball_fit(phi, z, 0.5)
    assert np.abs(c).sum() == pytest.approx(0.5)
    assert np.allclose(S.l1_ball_fit(phi, z, 1e9), S.ols(phi, z))
    exact, greedy = S.best_m_term(phi, z, 2, "exact"), S.best_m_term(phi, z, 2, "greedy")
    assert np.linalg.norm(z - phi @ exact) <= np.linalg.norm(z - phi @ greedy) + 1e-12


@pytest.mark.parametrize("kind", M.KINDS)
@pytest.mark.parametrize("b", [1, 2, 31, 32])
def test_mixers_are_orthogonal(kind, b):
    if kind == "wht" and b == 31:
        with pytest.raises(ValueError):
            M.mix(np.ones((31, 1)), kind)
        return
    x = np.random.default_rng(0).normal(size=(b, 3))
    r = M.rows_of(kind, b, np.arange(b))
    assert np.abs(r @ x - M.mix(x, kind)).max() < 1e-10 and np.abs(r @ r.T - np.eye(b)).max() < 1e-10
