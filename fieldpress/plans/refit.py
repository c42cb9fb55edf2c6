"""Re-estimation from the original points: the core by sketched or full least squares, an axis at a time, sizes by self-convergence."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame

from ..functions import basis as B
from ..operators import lstsq, sketch
from ..operators.design import columns, slices
from ..schema import coords
from .model import FunctionalTucker, ModeFunction


@dataclass
class Refit:
    model: FunctionalTucker
    s: int
    factor: float
    underdetermined: bool
    sketch_residual: float


def refit_core(points: DataFrame, model: FunctionalTucker, s: int | None = None, oversample: float = 2.5, mix: str = "dft", scope: str = "block", seed: int = 0, b: int = 1024, total: int | None = None, max_bytes: int | None = None) -> Refit:
    """The core from s mixed rows (oversample x R by default), of any R. Mixers: dft, dct, wht, none; projections: gauss, sparse_sign. Scopes: block, partition, global (dft)."""
    s = max(1, int(round(oversample * model.R))) if s is None else s
    if mix in ("gauss", "sparse_sign"):
        return _solved(model, *sketch.projected(points, model, s, mix, seed), seed)
    got = sketch.solve_sketch(points, model, s, mix, b, scope, seed, total, max_bytes)
    return Refit(model.with_core(got.core, seed=seed), got.rows, got.rows / model.R, got.rows < model.R, got.relative_residual)


def _solved(model: FunctionalTucker, a: np.ndarray, rhs: np.ndarray, seed: int) -> Refit:
    core = lstsq.solve_small(a, rhs) if len(rhs) else model.core.ravel()
    res, size = rhs - a @ core, float(rhs @ rhs)
    return Refit(model.with_core(core, seed=seed), len(rhs), len(rhs) / model.R, len(rhs) < model.R, float(np.sqrt(res @ res / size)) if size > 0 else 0.0)


def refit_sizes(points: DataFrame, model: FunctionalTucker, sizes: list[int], mix: str = "dft", seed: int = 0, b: int = 1024, total: int | None = None) -> list[Refit]:
    """``refit_core`` for several s from one sketch of the largest: the others are its first rows (sparse_sign: buckets of every size in one scan)."""
    if mix in ("gauss", "sparse_sign"):
        return [_solved(model, a, rhs, seed) for a, rhs in sketch.projections(points, model, sizes, mix, seed)]
    if max(sizes) * (model.R + 1) * 8 > sketch.MAX_SKETCH:
        return [refit_core(points, model, s, mix=mix, seed=seed, b=b, total=total) for s in sizes]
    a, rhs = sketch.sketch(points, model, max(sizes), mix, b, seed=seed, total=total)
    return [_solved(model, a[:s], rhs[:s], seed) for s in sizes]


def refit_full(points: DataFrame, model: FunctionalTucker, method: str = "gram") -> FunctionalTucker:
    """All points. A core that does not settle (only cores of over ``lstsq.MAX_R`` are iterated) is an error."""
    got = lstsq.full(points, model, method)
    if not got.converged:
        raise RuntimeError(f"the core did not settle in {got.rounds} rounds")
    return model.with_core(got.core)


def refit_top(points: DataFrame, model: FunctionalTucker, top: int) -> FunctionalTucker:
    """Only the ``top`` core entries of largest size are re-estimated; the others stay. For cores too large to solve."""
    d, flat = model.d, model.core.ravel().copy()
    at = np.lexsort((np.arange(flat.size), -np.abs(flat)))[:top]
    rest = flat.copy()
    rest[at] = 0

    def make(batches):
        out = np.zeros((top, top + 1))
        for batch in batches:
            for part in slices(batch, model.R):
                w = model.design(columns(part, d))
                u = part.column("u").to_numpy(zero_copy_only=False) - w @ rest
                out[:, :top] += w[:, at].T @ w[:, at]
                out[:, top] += w[:, at].T @ u
        return out

    block = lstsq.sum_blocks(points.select(*coords(d), "u"), make, (top, top + 1))
    if block is not None:
        flat[at] = lstsq.solve_gram(block[:, :top], block[:, top])[0]
    return model.with_core(flat)


def refit_axis(points: DataFrame, model: FunctionalTucker, k: int) -> FunctionalTucker:
    """All coefficients of axis k (on the union of its functions' bases' terms) with the rest fixed; the residual on the points cannot grow."""
    d = model.d
    specs = sorted({f.basis for f in model.functions[k]}, key=lambda s: (s.family, s.degree, s.resolution))
    terms = [(j, f.basis, i) for j, f in enumerate(model.functions[k]) for i in sorted(f.coef)]
    n = len(terms)
    if n == 0:
        return model
    jj = np.array([t[0] for t in terms])
    core = np.moveaxis(model.core, k, 0).reshape(model.ranks[k], -1)
    others = [m for m in range(d) if m != k]

    def make(batches):
        out = np.zeros((n, n + 1))
        for batch in batches:
            for part in slices(batch, max(n, model.R)):
                cols = columns(part, d)
                w = np.ones((part.num_rows, 1))
                for m in others:
                    w = (w[:, :, None] * model.mode_values(m, cols[m])[:, None, :]).reshape(part.num_rows, -1)
                g = w @ core.T  # rows by r_k
                x = model.unit(k, cols[k])
                values = {s: B.evaluate_matrix(x, s) for s in specs}
                phi = np.stack([values[s][:, i] for _, s, i in terms], axis=1) * g[:, jj]
                out[:, :n] += phi.T @ phi
                out[:, n] += phi.T @ part.column("u").to_numpy(zero_copy_only=False)
        return out

    block = lstsq.sum_blocks(points.select(*coords(d), "u"), make, (n, n + 1))
    if block is None:
        return model
    x, _ = lstsq.solve_gram(block[:, :n], block[:, n])
    new = [ModeFunction(f.basis, {}, f.fit_err, f.loo_err) for f in model.functions[k]]
    for (j, _, i), c in zip(terms, x):
        new[j].coef[i] = float(c)
    functions = [new if m == k else fs for m, fs in enumerate(model.functions)]
    return FunctionalTucker(model.axes, model.core, functions, model.meta)


def alternate(points: DataFrame, model: FunctionalTucker, sweeps: int = 1) -> FunctionalTucker:
    """Axis after axis, then the core."""
    for _ in range(sweeps):
        for k in range(model.d):
            model = refit_axis(points, model, k)
        model = refit_full(points, model)
    return model


def self_convergence(points: DataFrame, model: FunctionalTucker, sizes: list[int], step: int, mix: str = "dft", seed: int = 0, b: int = 1024, total: int | None = None) -> list[tuple[int, int, float]]:
    """(S1, S2, relative change of the core) for each S1 and S2 = S1 + step. One sketch of the largest size; the others are its first rows."""
    most = max(sizes) + step
    a, rhs = sketch.sketch(points, model, most, mix, b, seed=seed, total=total)
    solved = {}

    def core(s: int) -> np.ndarray:
        if s not in solved:
            solved[s] = lstsq.solve_small(a[:s], rhs[:s])
        return solved[s]

    out = []
    for s in sizes:
        x, y = core(s), core(s + step)
        size = float(np.linalg.norm(x))
        out.append((s, s + step, float(np.linalg.norm(y - x)) / size if size else 0.0))
    return out


def drop_at(changes: list[tuple[int, int, float]]) -> int | None:
    """The first S1 whose change is below a tenth of the largest change before it."""
    most = 0.0
    for s, _, c in changes:
        if most and c < most / 10:
            return s
        most = max(most, c)
    return None


def auto_size(points: DataFrame, model: FunctionalTucker, tol: float = 1e-2, step: int | None = None, start: float = 1.0, limit: float = 12.0, mix: str = "dft", seed: int = 0, b: int = 1024, total: int | None = None) -> tuple[Refit, list[tuple[int, int, float]]]:
    """Grow S until the core changes by less than ``tol``."""
    step = step or max(1, model.R // 2)
    sizes = list(range(max(1, int(start * model.R)), int(limit * model.R), step))
    changes = self_convergence(points, model, sizes, step, mix, seed, b, total)
    s = next((s2 for _, s2, c in changes if c < tol), changes[-1][1])
    return refit_core(points, model, s, mix=mix, seed=seed, b=b, total=total), changes
