"""Methods to compare with: full expansion, dense grid Tucker, local block quantiser, codec sizes."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.model import FunctionalTucker, ModeFunction
from ..schema import AxisSpec, BasisSpec
from . import lstsq, tucker
from .metrics import VALUE_BYTES, dense_tucker_bytes
from .sampling import cell_of


def full_expansion_size(bases: list[BasisSpec]) -> int:
    """Coefficients of the tensor-product space: the product of the axes' sizes."""
    return int(np.prod([b.size for b in bases], dtype=object))


def full_expansion_fit(points: DataFrame, axes: list[AxisSpec], bases: list[BasisSpec]) -> FunctionalTucker:
    """Least squares for every coefficient: a model whose functions are the basis functions themselves. Only for small spaces (at most ``lstsq.MAX_R`` coefficients)."""
    functions = [[ModeFunction(b, {i: 1.0}) for i in range(b.size)] for b in bases]
    model = FunctionalTucker(list(axes), np.zeros([b.size for b in bases]), functions)
    return model.with_core(lstsq.full(points, model).core)


#: Cell statistics are broadcast up to so many cells.
BROADCAST_CELLS = 200_000


@dataclass
class DenseTucker:
    result: tucker.TuckerResult
    dims: list[int]

    @property
    def bytes(self) -> int:
        return dense_tucker_bytes(self.result.ranks, self.dims)


def dense_tucker(tensor: DataFrame, dims: list[int], eps: float) -> DenseTucker:
    """The structured-grid method: core and factor columns are stored as they are."""
    return DenseTucker(tucker.st_hosvd(tensor, dims, eps), dims)


def block_quantise(points: DataFrame, axes: list[AxisSpec], bits: int = 8) -> DataFrame:
    """i1..id, n, lo, hi, mean, err2, sum2, bytes: each cell's values on 2^bits levels between its extremes. Two passes of partial aggregation, joined by cell."""
    idx = [f"i{k + 1}" for k in range(len(axes))]
    cells = points.select(*cell_of(axes), "u")
    stats = cells.groupBy(*idx).agg(F.count(F.lit(1)).alias("n"), F.min("u").alias("lo"), F.max("u").alias("hi"), F.avg("u").alias("mean"))
    # the grid is chosen, so its cells bound the broadcast; finer grids take a shuffled join
    few = int(np.prod([max(a.nodes - 1, 1) for a in axes])) <= BROADCAST_CELLS
    both = cells.join(F.broadcast(stats) if few else stats, idx)
    levels = float(2**bits - 1)
    width = (F.col("hi") - F.col("lo")) / levels
    code = F.when(width > 0, F.floor((F.col("u") - F.col("lo")) / width + 0.5)).otherwise(F.lit(0))
    back = F.col("lo") + code * width
    err = F.col("u") - back
    out = both.groupBy(*idx).agg(F.first("n").alias("n"), F.first("lo").alias("lo"), F.first("hi").alias("hi"), F.first("mean").alias("mean"), F.sum(err * err).alias("err2"), F.sum(F.col("u") * F.col("u")).alias("sum2"))
    return out.withColumn("bytes", 2 * VALUE_BYTES + F.col("n") * bits / 8)


def quantise_summary(quantised: DataFrame, q: int) -> dict[str, float]:
    r = quantised.agg(F.sum("err2").alias("e"), F.sum("sum2").alias("s"), F.sum("bytes").alias("b"), F.count(F.lit(1)).alias("cells")).first()
    return {"error": float(np.sqrt(r.e / r.s)) if r.s else 0.0, "bytes": float(r.b or 0), "ratio": VALUE_BYTES * q / r.b if r.b else 0.0, "cells": r.cells}


def single_space(points: DataFrame, axes: list[AxisSpec], space: BasisSpec, eps: float, **kw) -> FunctionalTucker:
    """Compression with one candidate space only."""
    from ..plans.compress import compress

    return compress(points, axes, eps, candidates=[space], **kw)
