"""Decoding: evaluating the formula at points, on grids and slices, over boxes. No shuffle."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import basis as B
from ..plans.model import FunctionalTucker
from ..schema import coords
from .design import columns, slices


def at_points(df: DataFrame, model: FunctionalTucker, cols: list[str] | None = None, name: str = "u_hat") -> DataFrame:
    """df with the model's value at its coordinate columns; null where a coordinate is null."""
    cols = cols or coords(model.d)
    names = df.columns
    width = max(model.ranks) * max(model.R // max(model.ranks), 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, width):
                x = [part.column(c).to_numpy(zero_copy_only=False).astype(float) for c in cols]
                v = model.evaluate([np.nan_to_num(c) for c in x])
                bad = np.zeros(part.num_rows, bool)
                for c in x:
                    bad |= np.isnan(c)
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(v, mask=bad)], names=[*names, name])

    return df.mapInArrow(run, T.StructType([*df.schema.fields, T.StructField(name, T.DoubleType())]))


def all_points(points: DataFrame, model: FunctionalTucker) -> DataFrame:
    return at_points(points, model)


def residuals(points: DataFrame, model: FunctionalTucker) -> DataFrame:
    """points with u_hat, resid, abs_resid."""
    return at_points(points, model).withColumn("resid", F.col("u") - F.col("u_hat")).withColumn("abs_resid", F.abs("resid"))


def _grid(spark: SparkSession, model: FunctionalTucker, values: list[np.ndarray]) -> DataFrame:
    """Decoded product of coordinate lists: axis functions once for each distinct coordinate, partitions along the first axis of more than one value."""
    d = model.d
    sizes = [len(v) for v in values]
    lead = next((k for k, n in enumerate(sizes) if n > 1), 0)
    # fixed axes are contracted first, so a slice costs its own nodes only
    x = model.core
    for k in sorted((k for k in range(d) if k != lead), key=lambda k: sizes[k]):
        x = np.moveaxis(np.tensordot(model.mode_values(k, values[k]), np.moveaxis(x, k, 0), axes=1), 0, k)
    first, rest = model.mode_values(lead, values[lead]), np.moveaxis(x, lead, 0)
    others = [k for k in range(d) if k != lead]
    idx = np.indices([sizes[k] for k in others]).reshape(len(others), -1) if others else np.zeros((0, 1), int)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in batch.column(0).to_pylist():
                v = np.tensordot(first[i], rest, axes=1).ravel()
                cols: list = [None] * d
                cols[lead] = pa.array(np.full(len(v), values[lead][i]))
                for k, at in zip(others, idx):
                    cols[k] = pa.array(values[k][at])
                yield pa.RecordBatch.from_arrays([*cols, pa.array(v)], names=[*coords(d), "u_hat"])

    return spark.range(sizes[lead]).mapInArrow(run, ", ".join(f"{c} double" for c in (*coords(d), "u_hat")))


def node_values(model: FunctionalTucker, k: int, nodes: int | None = None, lo: float | None = None, hi: float | None = None) -> np.ndarray:
    a = model.axes[k]
    return np.linspace(a.lo if lo is None else lo, a.hi if hi is None else hi, nodes or a.nodes)


def slice_at(spark: SparkSession, model: FunctionalTucker, fixed: dict[str, float], nodes: list[int] | None = None) -> DataFrame:
    """c1..cd, u_hat over the free axes' nodes with some axes (c1..cd or by name) fixed."""
    values = []
    for k, a in enumerate(model.axes):
        x = fixed.get(f"c{k + 1}", fixed.get(a.name))
        values.append(np.array([float(x)]) if x is not None else node_values(model, k, nodes[k] if nodes else None))
    return _grid(spark, model, values)


def box(spark: SparkSession, model: FunctionalTucker, ranges: dict[str, tuple[float, float]], nodes: list[int] | None = None) -> DataFrame:
    """c1..cd, u_hat over the nodes of a box; axes without a range are taken whole."""
    values = []
    for k, a in enumerate(model.axes):
        lo, hi = ranges.get(f"c{k + 1}", ranges.get(a.name, (a.lo, a.hi)))
        values.append(node_values(model, k, nodes[k] if nodes else None, lo, hi))
    return _grid(spark, model, values)


def box_mean(model: FunctionalTucker, ranges: dict[str, tuple[float, float]]) -> float:
    """The mean over a box, from integrals of the basis functions: no data are read."""
    x = model.core
    for k, a in reversed(list(enumerate(model.axes))):
        lo, hi = ranges.get(f"c{k + 1}", ranges.get(a.name, (a.lo, a.hi)))
        lo, hi = model.unit(k, np.array([lo, hi]))
        w = np.array([B.means(f.basis, float(lo), float(hi)) @ f.dense() for f in model.functions[k]])
        x = np.tensordot(x, w, axes=([k], [0]))
    return float(x)


def basis_evaluations(model: FunctionalTucker) -> int:
    """Basis functions evaluated for one point."""
    return sum(len({(f.basis, i) for f in fs for i in f.coef}) for fs in model.functions)


__all__ = ["all_points", "at_points", "basis_evaluations", "box", "box_mean", "columns", "residuals", "slice_at"]
