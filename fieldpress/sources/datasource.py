"""A model bundle as a table: spark.read.format("fieldpress").option("nodes", "50,50,20").load(dir).

Options: nodes (per axis), fix ("c3=0.4;c1=0.5"), pushdown. With pushdown=true, comparisons
of an axis column with a number are taken over by the reader and prune the nodes before
anything is evaluated; this needs spark.sql.python.filterPushdown.enabled. ``read`` sets
the option as the session allows. Register with ``register(spark)``.
"""

from __future__ import annotations

import glob
import os
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual

from ..plans.model import FunctionalTucker
from ..schema import coords


def load_local(path: str) -> FunctionalTucker:
    """A bundle from a path that the driver can open; for other stores use ``read``."""
    path = path.removeprefix("file://").removeprefix("file:")

    def rows(name: str) -> list[dict]:
        out = []
        for f in sorted(glob.glob(os.path.join(path, name, "*.parquet"))):
            out += pq.read_table(f).to_pylist()
        return out

    return FunctionalTucker.from_rows(*(rows(n) for n in ("axes", "mode_functions", "core", "meta")))


@dataclass
class Lead(InputPartition):
    """A range of the leading free axis."""

    start: int
    stop: int


class ModelSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "fieldpress"

    def _model(self) -> FunctionalTucker:
        return FunctionalTucker.from_json(self.options["model"]) if "model" in self.options else load_local(self.options["path"])

    def schema(self) -> str:
        return ", ".join(f"{c} double" for c in (*coords(self._model().d), "u_hat"))

    def reader(self, schema) -> "ModelReader":
        kind = PruningReader if self.options.get("pushdown", "false") == "true" else ModelReader
        return kind(self._model(), self.options)


class ModelReader(DataSourceReader):
    def __init__(self, model: FunctionalTucker, options):
        self.model = model
        nodes = [int(x) for x in options["nodes"].split(",")] if "nodes" in options else [a.nodes for a in model.axes]
        fixed = dict(x.split("=") for x in options.get("fix", "").split(";") if x)
        self.values = [np.array([float(fixed[f"c{k + 1}"])]) if f"c{k + 1}" in fixed else np.linspace(a.lo, a.hi, n) for k, (a, n) in enumerate(zip(model.axes, nodes))]

    def partitions(self) -> list[Lead]:
        n = len(self.values[0])
        step = max(1, -(-n // 16))
        return [Lead(i, min(i + step, n)) for i in range(0, n, step)] or [Lead(0, 0)]

    def read(self, partition: Lead) -> Iterator[pa.RecordBatch]:
        values = [self.values[0][partition.start : partition.stop], *self.values[1:]]
        if any(len(v) == 0 for v in values):
            return
        inner = self.model.core
        for k in sorted(range(1, self.model.d), key=lambda k: len(values[k])):
            inner = np.moveaxis(np.tensordot(self.model.mode_values(k, values[k]), np.moveaxis(inner, k, 0), axes=1), 0, k)
        grids = np.meshgrid(*values[1:], indexing="ij") if self.model.d > 1 else []
        lead = self.model.mode_values(0, values[0])
        for x, w in zip(values[0], lead):
            v = np.tensordot(w, inner, axes=1).ravel()
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(v), x)), *[pa.array(g.ravel()) for g in grids], pa.array(v)], names=[*coords(self.model.d), "u_hat"])


class PruningReader(ModelReader):
    """Takes comparisons over; Spark rejects such a reader where pushing down is switched off."""

    def pushFilters(self, filters: list[Filter]) -> Iterable[Filter]:
        for f in filters:
            name = f.attribute[0] if getattr(f, "attribute", None) and len(f.attribute) == 1 else ""
            k = coords(self.model.d).index(name) if name in coords(self.model.d) else -1
            keep = {GreaterThan: np.greater, GreaterThanOrEqual: np.greater_equal, LessThan: np.less, LessThanOrEqual: np.less_equal, EqualTo: np.equal}.get(type(f))
            if k < 0 or keep is None:
                yield f
            else:
                self.values[k] = self.values[k][keep(self.values[k], float(f.value))]


def register(spark: SparkSession) -> None:
    spark.dataSource.register(ModelSource)


def read(spark: SparkSession, path: str, **options: str):
    """The bundle, in any store that Spark reads, as a DataFrame, with pushdown if the session allows it: the model (as small as it is) travels in an option."""
    register(spark)
    options = {"model": FunctionalTucker.load(spark, path).to_json(), **options}
    on = spark.conf.get("spark.sql.python.filterPushdown.enabled", "false")
    return spark.read.format("fieldpress").options(pushdown=on, **options).load(path)
