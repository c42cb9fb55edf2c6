"""Sparse least squares in numpy: best m-term, l1 ball, Lasso path with leave-one-out choice.

Problems are tiny (one singular vector each); Spark runs one of them per group. The
objective of the penalised form is the squared residual plus lambda times the l1 norm, so
that an orthonormal design soft-thresholds at lambda / 2.
"""

from __future__ import annotations

from dataclasses import dataclass
from itertools import combinations

import numpy as np

TINY = 1e-12


@dataclass
class Knot:
    """A corner of the Lasso path: penalty, active columns, all coefficients."""

    lam: float
    active: tuple[int, ...]
    coef: np.ndarray


@dataclass
class SparseFit:
    coef: np.ndarray
    lam: float
    loo: float
    error: float

    @property
    def nnz(self) -> int:
        return int(np.count_nonzero(self.coef))


def ols(phi: np.ndarray, z: np.ndarray) -> np.ndarray:
    return np.linalg.lstsq(phi, z, rcond=None)[0]


def relative_error(phi: np.ndarray, z: np.ndarray, coef: np.ndarray) -> float:
    size = float(z @ z)
    r = z - phi @ coef
    return float(np.sqrt(r @ r / size)) if size > 0 else float(np.sqrt(r @ r))


# -- constrained forms -------------------------------------------------------------------


def best_m_term(phi: np.ndarray, z: np.ndarray, m: int, mode: str = "greedy", limit: int = 200_000) -> np.ndarray:
    """Least squares with at most m non-zeros. exact: all subsets (few columns only); orthonormal: the m largest coefficients; greedy: orthogonal matching pursuit."""
    p = phi.shape[1]
    m = min(m, p)
    out = np.zeros(p)
    if m == 0:
        return out
    if mode == "orthonormal":
        c = phi.T @ z
        keep = np.lexsort((np.arange(p), -np.abs(c)))[:m]
        out[keep] = c[keep]
        return out
    if mode == "exact":
        if np.prod([(p - i) / (i + 1) for i in range(m)]) > limit:
            raise ValueError(f"more than {limit} subsets of {m} of {p} columns")
        best = None
        for some in combinations(range(p), m):
            c = ols(phi[:, some], z)
            r = z - phi[:, some] @ c
            if best is None or r @ r < best[0] - TINY:
                best = (r @ r, some, c)
        out[list(best[1])] = best[2]
        return out
    if mode != "greedy":
        raise ValueError(f"unknown mode {mode!r}")
    norms = np.sqrt((phi * phi).sum(axis=0))
    norms[norms == 0] = np.inf
    chosen: list[int] = []
    r = z
    for _ in range(m):
        score = np.abs(phi.T @ r) / norms
        score[chosen] = -1
        j = int(score.argmax())
        if score[j] <= TINY * max(1.0, np.abs(z).max(initial=0)):
            break
        chosen.append(j)
        c = ols(phi[:, chosen], z)
        r = z - phi[:, chosen] @ c
    if chosen:
        out[chosen] = c
    return out


def l1_ball_fit(phi: np.ndarray, z: np.ndarray, delta: float) -> np.ndarray:
    """Least squares with an l1 norm of at most delta: the point of the Lasso path that has it."""
    path = lars_lasso_path(phi, z)
    return coef_at(path, lambda_for_delta(path, delta))


def lambda_for_delta(path: list[Knot], delta: float) -> float:
    """The penalty whose Lasso solution has l1 norm delta (0 if the bound does not bind)."""
    norms = [float(np.abs(k.coef).sum()) for k in path]
    if delta >= norms[-1]:
        return path[-1].lam
    for a, b, na, nb in zip(path, path[1:], norms, norms[1:]):
        if na <= delta <= nb and nb > na:
            return a.lam + (b.lam - a.lam) * (delta - na) / (nb - na)
    return path[0].lam


def lasso(phi: np.ndarray, z: np.ndarray, lam: float) -> np.ndarray:
    return coef_at(lars_lasso_path(phi, z), lam)


def coef_at(path: list[Knot], lam: float) -> np.ndarray:
    """Coefficients at a penalty: the path is linear between knots."""
    if lam >= path[0].lam:
        return np.zeros_like(path[0].coef)
    for a, b in zip(path, path[1:]):
        if b.lam <= lam:
            t = (a.lam - lam) / (a.lam - b.lam) if a.lam > b.lam else 1.0
            return a.coef + t * (b.coef - a.coef)
    return path[-1].coef


def lasso_cd(phi: np.ndarray, z: np.ndarray, lam: float, rounds: int = 5000, tol: float = 1e-13) -> np.ndarray:
    """The same minimiser by coordinate descent: an independent check."""
    v, r = np.zeros(phi.shape[1]), z.astype(float).copy()
    sq = (phi * phi).sum(axis=0)
    for _ in range(rounds):
        most = 0.0
        for j in range(len(v)):
            if sq[j] == 0:
                continue
            c = phi[:, j] @ r + sq[j] * v[j]
            new = np.sign(c) * max(abs(c) - lam / 2, 0) / sq[j]
            if new != v[j]:
                r += phi[:, j] * (v[j] - new)
                most = max(most, abs(new - v[j]))
                v[j] = new
        if most < tol:
            break
    return v


# -- path --------------------------------------------------------------------------------


class _Active:
    """The active columns with the inverse of their Gram matrix and the hat diagonal, kept by rank-one updates."""

    def __init__(self, phi: np.ndarray):
        self.phi, self.cols = phi, []
        self.inv = np.zeros((0, 0))
        self.hat = np.zeros(phi.shape[0])

    @property
    def matrix(self) -> np.ndarray:
        return self.phi[:, self.cols]

    def add(self, j: int) -> bool:
        """False if the column depends on those already there."""
        c = self.phi[:, j]
        a = self.matrix
        b = a.T @ c
        mb = self.inv @ b
        kappa = float(c @ c - b @ mb)
        if kappa <= 1e-10 * float(c @ c) or kappa <= 0:
            return False
        n = len(self.cols)
        grown = np.empty((n + 1, n + 1))
        grown[:n, :n] = self.inv + np.outer(mb, mb) / kappa
        grown[:n, n] = grown[n, :n] = -mb / kappa
        grown[n, n] = 1 / kappa
        self.hat = self.hat + (c - a @ mb) ** 2 / kappa
        self.inv = grown
        self.cols.append(j)
        return True

    def drop(self, at: int) -> None:
        m = self.inv[:, at]
        self.hat = self.hat - (self.matrix @ m) ** 2 / m[at]
        keep = [i for i in range(len(self.cols)) if i != at]
        self.inv = self.inv[np.ix_(keep, keep)] - np.outer(m[keep], m[keep]) / m[at]
        del self.cols[at]


def lars_lasso_path(phi: np.ndarray, z: np.ndarray, max_steps: int | None = None, loo: list[float] | None = None) -> list[Knot]:
    """All knots from the largest penalty down to 0 (or until the active set is full).

    Between knots the coefficients move linearly; the next knot is where an inactive column
    reaches the bound, an active coefficient reaches zero (the column is dropped), or the
    penalty is 0. If ``loo`` is a list it gets the leave-one-out error of least squares on
    the active set that leads to each knot.
    """
    rows, n = phi.shape
    corr = phi.T @ z
    lam = 2 * float(np.abs(corr).max(initial=0.0))
    path = [Knot(lam, (), np.zeros(n))]
    act = _Active(phi)
    if loo is not None:
        loo.append(fast_loo(phi[:, []], z))
    scale = lam
    if lam <= TINY * max(1.0, float(np.abs(z).max(initial=0.0))):
        return path
    banned: set[int] = set()
    v = np.zeros(n)
    sign = np.zeros(n)
    j = int(np.abs(corr).argmax())
    act.add(j)
    sign[j] = np.sign(corr[j])
    fresh, gone = j, -1
    cap = min(rows, n)
    for _ in range(max_steps or 8 * max(rows, n)):
        cols = np.array(act.cols)
        move = act.inv @ sign[cols] / 2
        slope = phi.T @ (act.matrix @ move)
        step, event = lam, ("end", -1)
        if len(cols) < cap:
            out = np.ones(n, bool)
            out[cols] = False
            out[list(banned)] = False
            for s in (1.0, -1.0):
                with np.errstate(divide="ignore", invalid="ignore"):
                    t = (lam - s * 2 * corr) / (1 - s * 2 * slope)
                bad = ~out | ~np.isfinite(t) | (t < -1e-12 * scale) | (1 - s * 2 * slope <= TINY)
                if gone >= 0:
                    bad[gone] |= t[gone] <= 1e-10 * scale
                t = np.where(bad, np.inf, np.maximum(t, 0))
                k = int(t.argmin())
                if t[k] < step:
                    step, event = float(t[k]), ("add", k)
        with np.errstate(divide="ignore", invalid="ignore"):
            t = -v[cols] / move
        t[(t <= 1e-14 * scale) | ~np.isfinite(t) | (cols == fresh)] = np.inf
        k = int(t.argmin())
        if t[k] < step:
            step, event = float(t[k]), ("drop", k)
        v = v.copy()
        v[cols] += step * move
        corr = corr - step * slope
        lam -= step
        fresh, gone = -1, -1
        if event[0] == "drop":
            v[cols[event[1]]] = 0.0
        path.append(Knot(max(lam, 0.0), tuple(int(c) for c in cols), v))
        if loo is not None:
            coef = act.inv @ (act.matrix.T @ z)
            loo.append(_loo(z - act.matrix @ coef, act.hat))
        if event[0] == "end" or lam <= 1e-13 * scale:
            break
        if event[0] == "drop":
            gone = int(cols[event[1]])
            sign[gone] = 0
            act.drop(event[1])
            if not act.cols:
                break
        elif act.add(event[1]):
            fresh = event[1]
            sign[fresh] = np.sign(corr[fresh])
        else:
            banned.add(event[1])
    return path


# -- leave-one-out -------------------------------------------------------------------------


def _loo(residual: np.ndarray, hat: np.ndarray) -> float:
    """Mean squared leave-one-out residual; infinite if some point has full leverage."""
    room = 1 - hat
    if len(room) and room.min() <= 1e-10:
        return float("inf")
    return float(np.mean((residual / room) ** 2)) if len(room) else 0.0


def fast_loo(phi: np.ndarray, z: np.ndarray) -> float:
    """Leave-one-out error of least squares without refitting: residuals over one less the hat diagonal."""
    if phi.shape[1] == 0:
        return float(np.mean(z**2)) if len(z) else 0.0
    q, r = np.linalg.qr(phi)
    if np.abs(np.diag(r)).min() <= 1e-10 * np.abs(np.diag(r)).max():
        return float("inf")
    return _loo(z - q @ (q.T @ z), (q * q).sum(axis=1))


def loo_bruteforce(phi: np.ndarray, z: np.ndarray) -> float:
    n = len(z)
    out = 0.0
    for i in range(n):
        keep = np.arange(n) != i
        out += float(z[i] - phi[i] @ ols(phi[keep], z[keep])) ** 2
    return out / n


def fit_lars_loo(phi: np.ndarray, z: np.ndarray, refit: str = "ols", max_steps: int | None = None) -> SparseFit:
    """The path's active set of least leave-one-out error (ties: fewer terms). Coefficients by least squares on it, or as on the path."""
    errors: list[float] = []
    path = lars_lasso_path(phi, z, max_steps, errors)
    floor = TINY * float(np.mean(z**2)) if len(z) else 0.0
    best = min(range(len(path)), key=lambda i: (max(errors[i], floor), len(path[i].active)))
    coef = path[best].coef
    if refit == "ols":
        coef = np.zeros(phi.shape[1])
        cols = list(path[best].active)
        if cols:
            coef[cols] = ols(phi[:, cols], z)
    size = float(np.var(z)) or float(np.mean(z**2)) or 1.0
    return SparseFit(coef, path[best].lam, errors[best] / size, relative_error(phi, z, coef))


def mutual_coherence(phi: np.ndarray) -> float:
    """Largest absolute cosine between two different columns."""
    norms = np.sqrt((phi * phi).sum(axis=0))
    phi = phi[:, norms > 0] / norms[norms > 0]
    g = np.abs(phi.T @ phi)
    np.fill_diagonal(g, 0)
    return float(g.max(initial=0.0))
