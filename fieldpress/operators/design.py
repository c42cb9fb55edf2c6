"""Design rows of the core regression: products of mode functions at each point.

The Q x R matrix is never stored: rows exist inside one Arrow batch, in slices of at most
``SLICE`` numbers.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from ..plans.model import FunctionalTucker
from ..schema import coords

SLICE = 16_000_000
#: Points that a task takes together, so that those of equal coordinates share their work.
HELD_POINTS = 65_536


def columns(batch: pa.RecordBatch, d: int) -> list[np.ndarray]:
    return [batch.column(c).to_numpy(zero_copy_only=False) for c in coords(d)]


def slices(batch: pa.RecordBatch, r: int) -> Iterator[pa.RecordBatch]:
    step = max(1, SLICE // max(r, 1))
    for i in range(0, batch.num_rows, step):
        yield batch.slice(i, step)


def held(batches: Iterator[pa.RecordBatch], names: list[str], most: int | None = None) -> Iterator[list[np.ndarray]]:
    """The batches' columns, so many rows together (None: ``HELD_POINTS``)."""
    most = HELD_POINTS if most is None else most
    kept: list[list[np.ndarray]] = []
    size = 0
    for batch in batches:
        for i in range(0, batch.num_rows, most):
            part = batch.slice(i, most)
            if size + part.num_rows > most:
                yield [np.concatenate(x) for x in zip(*kept)]
                kept, size = [], 0
            kept.append([part.column(n).to_numpy(zero_copy_only=False) for n in names])
            size += part.num_rows
    if size:
        yield [np.concatenate(x) for x in zip(*kept)]


def rows(points: DataFrame, model: FunctionalTucker) -> DataFrame:
    """pt_key, w (array of R products), u: for inspection; solvers keep the rows in their tasks."""
    d = model.d

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, model.R):
                w = model.design(columns(part, d))
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(w) + 1) * w.shape[1], pa.int32()), pa.array(w.ravel()))
                yield pa.RecordBatch.from_arrays([part.column("pt_key"), lists, part.column("u")], names=["pt_key", "w", "u"])

    return points.select("pt_key", *coords(d), "u").mapInArrow(run, "pt_key string, w array<double>, u double")
