"""Orthonormal bases on the unit interval, in numpy: evaluation, Gram matrices, integrals.

Legendre by the three-term recurrence; multiwavelets by completing the coarse space to the
fine one; piecewise Legendre cell by cell. At scale these run inside Arrow batches: cost is
the number of functions a point, memory one batch.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np

from ..schema import BasisSpec


def legendre_matrix(x: np.ndarray, degree: int) -> np.ndarray:
    """Values of the orthonormal Legendre polynomials of degrees 0..degree at x in [0, 1]."""
    t = 2 * np.asarray(x, float) - 1
    p = np.ones((len(t), degree + 1))
    if degree:
        p[:, 1] = t
    for m in range(1, degree):
        p[:, m + 1] = ((2 * m + 1) * t * p[:, m] - m * p[:, m - 1]) / (m + 1)
    return p * np.sqrt(2 * np.arange(degree + 1) + 1)


def _halves(x: np.ndarray, degree: int) -> np.ndarray:
    """Orthonormal local Legendre functions of the two half cells at x."""
    right = np.asarray(x) >= 0.5
    local = np.sqrt(2.0) * legendre_matrix(np.where(right, 2 * x - 1, 2 * x), degree)
    return np.concatenate([local * ~right[:, None], local * right[:, None]], axis=1)


@lru_cache(maxsize=None)
def mother_wavelets(degree: int) -> np.ndarray:
    """Coefficients of the degree + 1 mother wavelets on the half-cell functions (columns).

    The columns complete the coarse space within the fine one; they are rotated so that
    each has one more vanishing moment than the one before, and signed so that the largest
    entry is positive.
    """
    n = degree + 1
    g, w = np.polynomial.legendre.leggauss(n + 1)
    x = np.concatenate([(g + 1) / 4, (g + 1) / 4 + 0.5])
    w = np.concatenate([w, w]) / 4
    fine = _halves(x, degree)
    coarse = (fine * w[:, None]).T @ legendre_matrix(x, degree)  # 2n x n
    q, _ = np.linalg.qr(coarse, mode="complete")
    rest = q[:, n:]
    if degree:
        gx, gw = np.polynomial.legendre.leggauss(2 * n + 2)
        x2, w2 = np.concatenate([(gx + 1) / 4, (gx + 1) / 4 + 0.5]), np.concatenate([gw, gw]) / 4
        higher = legendre_matrix(x2, 2 * n)[:, n : 2 * n]  # orthogonal moments of degrees n .. 2n - 1
        moments = (higher * w2[:, None]).T @ (_halves(x2, degree) @ rest)
        turn, _ = np.linalg.qr(moments.T)
        rest = rest @ turn
    size = np.abs(rest)
    top = (size >= size.max(axis=0) - 1e-9).argmax(axis=0)  # the first of equals
    return rest * np.sign(rest[top, np.arange(n)])


def multiwavelet_matrix(x: np.ndarray, levels: int, degree: int) -> np.ndarray:
    """Scaling functions, then wavelets by level, cell and mother. x = 1 belongs to the last cell."""
    x = np.asarray(x, float)
    n = degree + 1
    out = np.zeros((len(x), n * 2**levels))
    out[:, :n] = legendre_matrix(x, degree)
    mothers = mother_wavelets(degree)
    rows = np.arange(len(x))[:, None]
    for level in range(levels):
        cells = 2**level
        cell = np.clip(np.floor(x * cells).astype(int), 0, cells - 1)
        value = np.sqrt(cells) * (_halves(x * cells - cell, degree) @ mothers)
        out[rows, n * cells + (cell * n)[:, None] + np.arange(n)] = value
    return out


def piecewise_matrix(x: np.ndarray, levels: int, degree: int) -> np.ndarray:
    x = np.asarray(x, float)
    n, cells = degree + 1, 2**levels
    cell = np.clip(np.floor(x * cells).astype(int), 0, cells - 1)
    out = np.zeros((len(x), n * cells))
    out[np.arange(len(x))[:, None], (cell * n)[:, None] + np.arange(n)] = np.sqrt(cells) * legendre_matrix(x * cells - cell, degree)
    return out


def evaluate_matrix(x: np.ndarray, spec: BasisSpec) -> np.ndarray:
    """len(x) by spec.size values of the basis functions."""
    if spec.family == "legendre":
        return legendre_matrix(x, spec.degree)
    if spec.family == "multiwavelet":
        return multiwavelet_matrix(x, spec.levels, spec.degree)
    if spec.family == "piecewise":
        return piecewise_matrix(x, spec.levels, spec.degree)
    raise ValueError(f"unknown family {spec.family!r}")


def _legendre_rows(x: np.ndarray, degree: int) -> np.ndarray:
    """``legendre_matrix`` transposed, each polynomial in one piece of memory."""
    t = 2 * x - 1
    p = np.ones((degree + 1, len(t)))
    if degree:
        p[1] = t
    for m in range(1, degree):
        p[m + 1] = ((2 * m + 1) * t * p[m] - m * p[m - 1]) / (m + 1)
    return p * np.sqrt(2 * np.arange(degree + 1) + 1)[:, None]


@lru_cache(maxsize=None)
def _local_change(levels: int, degree: int) -> np.ndarray:
    """Coefficients of the multiwavelets (columns) on the finest cells' local functions."""
    x, w = quadrature(0.0, 1.0, BasisSpec("multiwavelet", degree, levels))
    return (piecewise_matrix(x, levels, degree) * w[:, None]).T @ multiwavelet_matrix(x, levels, degree)


def combine(x: np.ndarray, spec: BasisSpec, coef: np.ndarray, step: int = 16384) -> np.ndarray:
    """``evaluate_matrix(x, spec) @ coef`` for many x: polynomials by rows of memory, wavelets as one polynomial a cell."""
    x = np.asarray(x, float)
    out = np.empty((len(x), coef.shape[1]))
    if spec.family != "multiwavelet":
        for i in range(0, len(x), step):
            part = x[i : i + step]
            out[i : i + step] = (_legendre_rows(part, spec.degree).T if spec.family == "legendre" else evaluate_matrix(part, spec)) @ coef
        return out
    cells = 2**spec.levels
    local = np.sqrt(cells) * (_local_change(spec.levels, spec.degree) @ coef).reshape(cells, spec.degree + 1, -1)
    cell = np.clip(np.floor(x * cells).astype(int), 0, cells - 1)
    for k in range(cells):
        at = np.flatnonzero(cell == k)
        out[at] = _legendre_rows(x[at] * cells - k, spec.degree).T @ local[k]
    return out


def _pieces(a: float, b: float, levels: int) -> np.ndarray:
    inner = np.arange(1, 2**levels) / 2**levels
    return np.concatenate([[a], inner[(inner > a) & (inner < b)], [b]])


def quadrature(a: float, b: float, spec: BasisSpec, more: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Nodes and weights, exact for products of two basis functions on [a, b]."""
    g, w = np.polynomial.legendre.leggauss(spec.degree + 1 + more)
    edges = _pieces(a, b, spec.levels)
    half = np.diff(edges)[:, None] / 2
    return (edges[:-1, None] + half * (g + 1)).ravel(), (half * w).ravel()


def gram(spec: BasisSpec) -> np.ndarray:
    """Inner products of the basis functions; the identity."""
    x, w = quadrature(0.0, 1.0, spec)
    phi = evaluate_matrix(x, spec)
    return phi.T @ (phi * w[:, None])


def means(spec: BasisSpec, a: float, b: float) -> np.ndarray:
    """Mean of every basis function over [a, b]; its value at a if a = b."""
    if b <= a:
        return evaluate_matrix(np.array([a]), spec)[0]
    x, w = quadrature(a, b, spec)
    return (w @ evaluate_matrix(x, spec)) / (b - a)
