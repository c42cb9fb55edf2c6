"""Compression: regrid a share of the points, decompose, turn singular vectors into functions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame

from ..operators import axes as AX
from ..operators import funcfit, regrid, sampling, tucker
from ..operators.storage import cut
from ..schema import AxisSpec, BasisSpec, indices, legendre, multiwavelet
from .model import FunctionalTucker, Meta

#: Candidates on any axis: those with fewer functions than the axis has nodes are tried, polynomials of a degree that fits.
DEFAULT_SPACES = [legendre(40), multiwavelet(5, 3), multiwavelet(3, 3), multiwavelet(2, 3), multiwavelet(1, 3)]


def grid_tensor(points: DataFrame, axes: list[AxisSpec], rate: float = 1.0, regridder: str = "local_linear", seed: int = 0, **kw) -> DataFrame:
    """All nodes of the grid from a share of the points; uncovered nodes are filled. Written once: later steps read it several times."""
    part = sampling.hash_fraction(points, rate, seed)
    tensor = cut(regrid.REGRIDDERS[regridder](part, axes, **kw), "tensor")
    return regrid.fill_holes(tensor, axes)


def compress(points: DataFrame, axes: list[AxisSpec], eps: float | None = 1e-2, rate: float = 1.0, regridder: str = "local_linear", candidates: list[BasisSpec] | dict | None = None, *, ranks: list[int] | None = None, criterion: str = "loo", solver: str = "lars_loo", seed: int = 0, mode_order=None, tensor: DataFrame | None = None, n_points: int | None = None) -> FunctionalTucker:
    """The model before its core is re-estimated. Everything but I x I matrices, the core and the vectors stays on the executors."""
    spark = points.sparkSession
    t = grid_tensor(points, axes, rate, regridder, seed) if tensor is None else tensor
    dims = [a.nodes for a in axes]
    found = tucker.st_hosvd(t.select(*indices(len(axes)), "v"), dims, eps if ranks is None else None, ranks, mode_order)
    functions = funcfit.fit_functions(spark, found.factors, axes, candidates or DEFAULT_SPACES, criterion, solver)
    err = fit_error(found, functions, axes)
    meta = Meta(eps or 0.0, rate, found.error, err, 0.0, points.count() if n_points is None else n_points, seed, {"regridder": regridder, "criterion": criterion, "solver": solver})
    return FunctionalTucker(list(axes), found.core, functions, meta)


def fit_error(found: tucker.TuckerResult, functions, axes: list[AxisSpec]) -> float:
    """Relative change that replacing vectors by functions makes at the grid nodes, from small matrices only: |core x W - core x W'| by Gram products."""
    approx = [np.stack([f(funcfit.unit_nodes(a)) for f in fs], axis=1) for fs, a in zip(functions, axes)]
    norm = float((found.core**2).sum())
    if norm == 0:
        return 0.0
    cross, own = found.core, found.core
    for k, (w, x) in enumerate(zip(found.factors, approx)):
        cross = np.moveaxis(np.tensordot(w.T @ x, np.moveaxis(cross, k, 0), axes=1), 0, k)
        own = np.moveaxis(np.tensordot(x.T @ x, np.moveaxis(own, k, 0), axes=1), 0, k)
    d2 = norm - 2 * float((found.core * cross).sum()) + float((found.core * own).sum())
    return float(np.sqrt(max(d2, 0.0) / norm))


def default_axes(nodes: list[int]) -> list[AxisSpec]:
    return AX.unit_axes(nodes)
