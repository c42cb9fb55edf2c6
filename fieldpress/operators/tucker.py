"""Tucker decomposition by higher-order SVD, sequentially truncated or classical.

Each mode: fibers, Gram matrix, eigenvectors on the driver (I x I), rank cut, product. In
the sequential form the next mode sees the shrunk tensor. A tensor of at most
``LOCAL_CELLS`` cells (a grid is chosen, it does not grow with the data) is decomposed on the driver with
the same arithmetic; larger ones take one shuffle a mode and nothing of tensor size is
collected but the core.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..schema import indices
from . import tensor_ops as ops
from .storage import cut

LOCAL_CELLS = 2_000_000


@dataclass
class TuckerResult:
    core: np.ndarray
    factors: list[np.ndarray]
    spectra: list[np.ndarray]
    norm2: float
    discarded: float
    order: list[int] = field(default_factory=list)

    @property
    def ranks(self) -> tuple[int, ...]:
        return self.core.shape

    @property
    def error(self) -> float:
        """Relative error that the truncation accounts for."""
        return float(np.sqrt(max(self.discarded, 0.0) / self.norm2)) if self.norm2 > 0 else 0.0


def eigen(gram: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Eigenvalues (descending, none negative) and vectors whose largest entry is positive."""
    w, v = np.linalg.eigh(gram)
    w, v = np.maximum(w[::-1], 0.0), v[:, ::-1]
    size = np.abs(v)
    top = (size >= size.max(axis=0) - 1e-9).argmax(axis=0)
    sign = np.sign(v[top, np.arange(v.shape[1])])
    return w, v * np.where(sign == 0, 1, sign)


def cut_rank(spectrum: np.ndarray, budget: float) -> int:
    """The smallest rank, 1 at least, whose discarded eigenvalues sum to at most the budget."""
    tail = np.concatenate([np.cumsum(spectrum[::-1])[::-1], [0.0]])
    return max(1, int(np.argmax(tail <= budget)))


def _plan(dims: list[int], eps: float | None, ranks: list[int] | None, norm2: float):
    if (eps is None) == (ranks is None):
        raise ValueError("give either eps or ranks")
    share = 0.0 if eps is None else eps * eps * norm2 / len(dims)
    return lambda k, spectrum: min(ranks[k], len(spectrum)) if ranks is not None else cut_rank(spectrum, share)


def _order(dims: list[int], mode_order) -> list[int]:
    if mode_order == "largest":
        return sorted(range(len(dims)), key=lambda k: (-dims[k], k))
    return list(mode_order) if mode_order is not None else list(range(len(dims)))


def numpy_st_hosvd(array: np.ndarray, eps: float | None = None, ranks: list[int] | None = None, mode_order=None) -> TuckerResult:
    norm2 = float((array * array).sum())
    pick = _plan(list(array.shape), eps, ranks, norm2)
    order = _order(list(array.shape), mode_order)
    factors: list = [None] * array.ndim
    spectra: list = [None] * array.ndim
    discarded, x = 0.0, array
    for k in order:
        flat = np.moveaxis(x, k, 0).reshape(x.shape[k], -1)
        w, v = eigen(flat @ flat.T)
        r = pick(k, w)
        factors[k], spectra[k] = v[:, :r], w
        discarded += float(w[r:].sum())
        x = np.moveaxis(np.tensordot(v[:, :r].T, np.moveaxis(x, k, 0), axes=1), 0, k)
    return TuckerResult(x, factors, spectra, norm2, discarded, order)


def st_hosvd(tensor: DataFrame, dims: list[int], eps: float | None = None, ranks: list[int] | None = None, mode_order=None, local_cells: int = LOCAL_CELLS) -> TuckerResult:
    """Sequentially truncated: by precision (tails of at most eps^2 |T|^2 / d a mode) or by given ranks. mode_order: a list, ``largest`` or natural."""
    if int(np.prod(dims)) <= local_cells:
        return numpy_st_hosvd(ops.to_numpy(tensor, dims), eps, ranks, mode_order)
    norm2 = ops.norm2(tensor)
    pick = _plan(dims, eps, ranks, norm2)
    order = _order(dims, mode_order)
    now, x, discarded = list(dims), tensor, 0.0
    factors: list = [None] * len(dims)
    spectra: list = [None] * len(dims)
    for k in order:
        vectors = cut(ops.fibers(x, now, k), "fibers")
        w, v = eigen(ops.gram(vectors, now[k]))
        r = pick(k, w)
        factors[k], spectra[k] = v[:, :r], w
        discarded += float(w[r:].sum())
        now[k] = r
        x = ops.unfiber(ops.multiply_fibers(vectors, v[:, :r]), now, k)
    return TuckerResult(ops.to_numpy(x, now), factors, spectra, norm2, discarded, order)


def t_hosvd(tensor: DataFrame, dims: list[int], eps: float | None = None, ranks: list[int] | None = None, local_cells: int = LOCAL_CELLS) -> TuckerResult:
    """Classical: all Gram matrices from the whole tensor, then all products."""
    local = int(np.prod(dims)) <= local_cells
    array = ops.to_numpy(tensor, dims) if local else None
    norm2 = float((array * array).sum()) if local else ops.norm2(tensor)
    pick = _plan(dims, eps, ranks, norm2)
    factors, spectra = [], []
    for k in range(len(dims)):
        if local:
            flat = np.moveaxis(array, k, 0).reshape(dims[k], -1)
            w, v = eigen(flat @ flat.T)
        else:
            w, v = eigen(ops.gram(ops.fibers(tensor, dims, k), dims[k]))
        factors.append(v[:, : pick(k, w)])
        spectra.append(w)
    if local:
        x = array
        for k, f in enumerate(factors):
            x = np.moveaxis(np.tensordot(f.T, np.moveaxis(x, k, 0), axes=1), 0, k)
    else:
        now, rows = list(dims), tensor
        for k, f in enumerate(factors):
            rows = ops.mode_product(rows, now, f, k)
            now[k] = f.shape[1]
        x = ops.to_numpy(rows, now)
    return TuckerResult(x, factors, spectra, norm2, norm2 - float((x * x).sum()), list(range(len(dims))))


def expand(core: np.ndarray, factors: list[np.ndarray]) -> np.ndarray:
    x = core
    for k, f in enumerate(factors):
        x = np.moveaxis(np.tensordot(f, np.moveaxis(x, k, 0), axes=1), 0, k)
    return x


def reconstruct(spark, result: TuckerResult) -> DataFrame:
    """All cells (i1..id, v), computed on the executors: leading axis by leading axis, no shuffle."""
    from collections.abc import Iterator

    import pyarrow as pa

    dims = [f.shape[0] for f in result.factors]
    core, factors = result.core, result.factors
    d = len(dims)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        inner = core
        for k in range(1, d):  # all axes but the first once
            inner = np.moveaxis(np.tensordot(factors[k], np.moveaxis(inner, k, 0), axes=1), 0, k)
        idx = np.indices(dims[1:]).reshape(d - 1, -1) if d > 1 else np.zeros((0, 1), int)
        for batch in batches:
            for i in batch.column(0).to_pylist():
                v = np.tensordot(factors[0][i], inner, axes=1).ravel()
                cols = [pa.array(np.full(len(v), i), pa.int32()), *[pa.array(x, pa.int32()) for x in idx], pa.array(v)]
                yield pa.RecordBatch.from_arrays(cols, names=[*indices(d), "v"])

    schema = ", ".join(f"{i} int" for i in indices(d)) + ", v double"
    return spark.range(dims[0]).mapInArrow(run, schema)


def relative_error(truth: DataFrame, estimate: DataFrame, d: int) -> float:
    """Relative Frobenius distance of two tensors of rows; a cell that one lacks counts as 0."""
    a, b = truth.select(*indices(d), "v"), estimate.select(*indices(d), F.col("v").alias("e"))
    diff = F.coalesce("v", F.lit(0.0)) - F.coalesce("e", F.lit(0.0))
    row = a.join(b, indices(d), "full").agg(F.sum(diff * diff).alias("n"), F.sum(F.col("v") * F.col("v")).alias("q")).first()
    return float(np.sqrt((row.n or 0.0) / row.q)) if row.q else 0.0
