"""Singular vectors as sparse functions: one fit for each vector and candidate space.

The fits are independent and tiny, so they are rows of a DataFrame and run in Arrow
batches; the choice of the space is a ranking window.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import basis as B
from ..functions import sparse as S
from ..plans.model import ModeFunction
from ..schema import AxisSpec, BasisSpec

SAMPLES = "k int, j int, y array<double>, z array<double>"
FITS = "k int, j int, basis struct<family:string,degree:int,resolution:int>, coef map<int,double>, nnz int, n int, fit_err double, loo_err double"


def unit_nodes(a: AxisSpec) -> np.ndarray:
    return np.linspace(0, 1, a.nodes) if a.nodes > 1 else np.zeros(1)


def vector_samples(spark: SparkSession, factors: list[np.ndarray], axes: list[AxisSpec]) -> DataFrame:
    """k, j, y, z: each singular vector's values at the axis nodes (unit coordinates)."""
    rows = [(k + 1, j + 1, unit_nodes(a).tolist(), f[:, j].tolist()) for k, (a, f) in enumerate(zip(axes, factors)) for j in range(f.shape[1])]
    return spark.createDataFrame(rows, SAMPLES)


def solve(y: np.ndarray, z: np.ndarray, spec: BasisSpec, solver: str = "lars_loo") -> S.SparseFit:
    """One fit. ols: all functions; lars_loo: Lasso path, leave-one-out choice, least squares on the chosen functions; lasso_loo: the path's own values; lars_or_ols: all functions if their leave-one-out error is below half of the path's."""
    phi = B.evaluate_matrix(y, spec)
    if solver == "ols":
        coef = S.ols(phi, z)
        size = float(np.var(z)) or float(np.mean(z**2)) or 1.0
        return S.SparseFit(coef, 0.0, S.fast_loo(phi, z) / size, S.relative_error(phi, z, coef))
    fit = S.fit_lars_loo(phi, z, "lasso" if solver == "lasso_loo" else "ols")
    if solver == "lars_or_ols" and spec.size < len(z):
        full = solve(y, z, spec, "ols")
        if full.loo < 0.5 * fit.loo:
            return full
    return fit


def capped(specs: list[BasisSpec], nodes: int) -> list[BasisSpec]:
    """The spaces that have fewer functions than the axis has nodes; polynomials are lowered to fit. One constant if nothing does."""
    out: list[BasisSpec] = []
    for s in specs:
        if s.family == "legendre":
            s = BasisSpec("legendre", max(0, min(s.degree, nodes - 2)))
        if s.size < nodes or s.size == 1:
            if s not in out:
                out.append(s)
    return out or [BasisSpec("legendre", 0)]


def fit_all(samples: DataFrame, specs: list[BasisSpec] | dict[int, list[BasisSpec]], solver: str = "lars_loo") -> DataFrame:
    """A row for each vector and candidate space (``FITS``). specs may differ by axis."""

    def of(k: int, n: int) -> list[BasisSpec]:
        return capped(specs[k] if isinstance(specs, dict) else specs, n)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for r in batch.to_pylist():
                y, z = np.array(r["y"]), np.array(r["z"])
                for spec in of(r["k"], len(y)):
                    fit = solve(y, z, spec, solver)
                    coef = [(int(i), float(fit.coef[i])) for i in np.flatnonzero(fit.coef)]
                    out.append({"k": r["k"], "j": r["j"], "basis": spec.row(), "coef": coef, "nnz": len(coef), "n": spec.size, "fit_err": fit.error, "loo_err": fit.loo})
            yield pa.RecordBatch.from_pylist(out, schema=_FITS_ARROW)

    n = samples.sparkSession.sparkContext.defaultParallelism
    return samples.repartition(n, "k", "j").mapInArrow(run, FITS)


_FITS_ARROW = pa.schema([("k", pa.int32()), ("j", pa.int32()), ("basis", pa.struct([("family", pa.string()), ("degree", pa.int32()), ("resolution", pa.int32())])), ("coef", pa.map_(pa.int32(), pa.float64())), ("nnz", pa.int32()), ("n", pa.int32()), ("fit_err", pa.float64()), ("loo_err", pa.float64())])


def best(fits: DataFrame, criterion: str = "loo") -> DataFrame:
    """The space of least error for each vector; errors within 1e-12 count as equal, then fewer terms, then the smaller space."""
    err = F.greatest(F.col("loo_err") if criterion == "loo" else F.col("fit_err"), F.lit(1e-12))
    w = Window.partitionBy("k", "j").orderBy(err, "nnz", "n", "basis.family")
    return fits.withColumn("r", F.row_number().over(w)).where("r = 1").drop("r")


def fit_best(samples: DataFrame, specs, criterion: str = "loo", solver: str = "lars_loo") -> DataFrame:
    return best(fit_all(samples, specs, solver), criterion)


def to_functions(rows, d: int) -> list[list[ModeFunction]]:
    out: list[list[ModeFunction]] = [[] for _ in range(d)]
    for r in sorted(rows, key=lambda r: (r["k"], r["j"])):
        b = r["basis"]
        out[r["k"] - 1].append(ModeFunction(BasisSpec(b["family"], b["degree"], b["resolution"]), dict(r["coef"]), r["fit_err"], r["loo_err"]))
    return out


def fit_functions(spark: SparkSession, factors: list[np.ndarray], axes: list[AxisSpec], specs, criterion: str = "loo", solver: str = "lars_loo") -> list[list[ModeFunction]]:
    return to_functions(fit_best(vector_samples(spark, factors, axes), specs, criterion, solver).collect(), len(axes))


def richness_sweep(samples: DataFrame, specs: list[BasisSpec], solver: str = "ols") -> DataFrame:
    """space, n, nnz, fit_err, loo_err for growing spaces."""
    f = fit_all(samples, specs, solver)
    name = F.when(F.col("basis.family") == "legendre", F.concat(F.lit("legendre("), F.col("basis.degree"), F.lit(")"))).otherwise(F.concat(F.col("basis.family"), F.lit("("), F.col("basis.resolution"), F.lit(","), F.col("basis.degree"), F.lit(")")))
    return f.select("k", "j", name.alias("space"), "n", "nnz", "fit_err", "loo_err")


def grouped_line_loo(df: DataFrame, key: str, y: str, z: str) -> DataFrame:
    """key, loo: leave-one-out error of a line for each group, as a grouped aggregate over Arrow. A group is one task's: use it for bounded groups (for whole tables the two-aggregate form needs no grouping)."""

    @F.pandas_udf("double")
    def loo(a: pd.Series, b: pd.Series) -> float:
        x = a.to_numpy(float)
        return float(S.fast_loo(np.column_stack([np.ones(len(x)), x]), b.to_numpy(float)))

    return df.groupBy(key).agg(loo(y, z).alias("loo"))
