"""Accuracy, storage and cost measures."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.model import FunctionalTucker
from ..schema import AxisSpec, coords
from . import decode
from .design import columns, slices
from .funcfit import unit_nodes
from .lstsq import SharedRows, held, sum_blocks
from .sampling import hash_fraction

VALUE_BYTES = 8
INDEX_BYTES = 4
TAG_BYTES = 12


def rel_fro(df: DataFrame, truth: str = "u", estimate: str = "u_hat") -> float:
    """Relative Frobenius error of two columns; one aggregate."""
    row = error_sums(df, truth, estimate).first()
    return float(np.sqrt(row.num / row.den)) if row.den else 0.0


def error_sums(df: DataFrame, truth: str = "u", estimate: str = "u_hat") -> DataFrame:
    e = F.col(truth) - F.col(estimate)
    return df.agg(F.coalesce(F.sum(e * e), F.lit(0.0)).alias("num"), F.coalesce(F.sum(F.col(truth) * F.col(truth)), F.lit(0.0)).alias("den"), F.count(F.lit(1)).alias("n"))


def achieved_error(points: DataFrame, model: FunctionalTucker, rate: float = 1.0, seed: int = 0) -> tuple[float, float, int]:
    """(error, two standard errors, rows) over all points, or over a hash sample with the spread of the ratio estimator."""
    df = decode.residuals(hash_fraction(points, rate, f"err{seed}"), model)
    e2, u2 = F.col("resid") * F.col("resid"), F.col("u") * F.col("u")
    r = df.agg(F.sum(e2).alias("a"), F.sum(u2).alias("b"), F.sum(e2 * e2).alias("aa"), F.sum(u2 * u2).alias("bb"), F.sum(e2 * u2).alias("ab"), F.count(F.lit(1)).alias("n")).first()
    if not r.n or not r.b:
        return 0.0, 0.0, r.n or 0
    q = r.a / r.b
    if rate >= 1:
        return float(np.sqrt(q)), 0.0, r.n
    var = max(r.aa - 2 * q * r.ab + q * q * r.bb, 0.0) / r.b**2
    return float(np.sqrt(q)), float(np.sqrt(var) / np.sqrt(max(q, 1e-300))), r.n


def shared_error(points: DataFrame, model: FunctionalTucker) -> float:
    """Relative error over all points, for large cores: an axis of few distinct coordinates is contracted once for all points of each."""

    def make(batches):
        out = np.zeros(2)
        for *cols, u in held(batches, [*coords(model.d), "u"]):
            e = u - SharedRows(model, cols).values(model.core)
            out += e @ e, u @ u
        return out

    got = sum_blocks(points.select(*coords(model.d), "u"), make, (2,))
    return 0.0 if got is None or not got[1] else float(np.sqrt(got[0] / got[1]))


def core_errors(points: DataFrame, model: FunctionalTucker, cores: list[np.ndarray]) -> list[float]:
    """Relative error over all points of the model with each of some cores: one scan, in which they share the design rows."""
    c = np.stack([np.asarray(x, float).ravel() for x in cores], axis=1)
    k = c.shape[1]

    def make(batches):
        out = np.zeros(k + 1)
        for batch in batches:
            for part in slices(batch, max(model.R, k)):
                u = part.column("u").to_numpy(zero_copy_only=False)
                e = u[:, None] - model.design(columns(part, model.d)) @ c
                out[:k] += (e * e).sum(axis=0)
                out[k] += u @ u
        return out

    got = sum_blocks(points.select(*coords(model.d), "u"), make, (k + 1,))
    return [0.0] * k if got is None or not got[k] else np.sqrt(got[:k] / got[k]).tolist()


def pointwise(spark: SparkSession, factors: list[np.ndarray], functions, axes: list[AxisSpec]) -> DataFrame:
    """k, j, i, y, exact, approx, abs_err: each singular vector against its function, node by node."""
    rows = []
    for k, (w, fs, a) in enumerate(zip(factors, functions, axes)):
        x = unit_nodes(a)
        for j, f in enumerate(fs):
            got = f(x)
            rows += [(k + 1, j + 1, i, a.node(i), float(e), float(g), float(abs(e - g))) for i, (e, g) in enumerate(zip(w[:, j], got))]
    return spark.createDataFrame(rows, "k int, j int, i int, y double, exact double, approx double, abs_err double")


def core_decay(core: DataFrame) -> DataFrame:
    """rank, abs_core, cum_energy: core entries by size on a canonical rank axis. core: (j, v)."""
    w = Window.orderBy(F.desc(F.abs("v")), "j")
    return core.select(F.row_number().over(w).alias("rank"), F.abs("v").alias("abs_core"), (F.sum(F.col("v") * F.col("v")).over(w.rowsBetween(Window.unboundedPreceding, 0)) / F.sum(F.col("v") * F.col("v")).over(Window.partitionBy())).alias("cum_energy"))


def leverage_histogram(df: DataFrame, edges: list[float], col: str = "lev") -> DataFrame:
    """bucket, lo, hi, n over the edges; the last bucket is closed. Empty buckets are left out."""
    b = F.lit(None).cast("int")
    for i in reversed(range(len(edges) - 1)):
        top = F.col(col) <= edges[i + 1] if i == len(edges) - 2 else F.col(col) < edges[i + 1]
        b = F.when((F.col(col) >= edges[i]) & top, F.lit(i)).otherwise(b)
    lo = F.element_at(F.array(*map(F.lit, edges)), F.col("bucket") + 1)
    hi = F.element_at(F.array(*map(F.lit, edges)), F.col("bucket") + 2)
    return df.select(b.alias("bucket")).where("bucket IS NOT NULL").groupBy("bucket").agg(F.count(F.lit(1)).alias("n")).select("bucket", lo.alias("lo"), hi.alias("hi"), "n")


def leverage_spread(df: DataFrame, col: str = "lev") -> dict[str, float]:
    """Maximum over mean, share within [0.2, 0.5], coefficient of variation."""
    r = df.agg(F.max(col).alias("m"), F.avg(col).alias("a"), F.stddev_pop(col).alias("s"), F.avg(F.col(col).between(0.2, 0.5).cast("double")).alias("mid")).first()
    return {"max_over_mean": r.m / r.a, "in_02_05": r.mid, "cv": r.s / r.a, "mean": r.a}


def original_bytes(q: int) -> int:
    return VALUE_BYTES * q


def storage(model: FunctionalTucker, q: int | None = None) -> dict[str, float]:
    """values_only (values alone, as the published ratios count), with_indices, original, and both ratios."""
    q = model.meta.n_points if q is None else q
    values = VALUE_BYTES * (model.R + model.nnz)
    tags = sum(len(f) for f in model.functions) * TAG_BYTES + len(model.axes) * (3 * VALUE_BYTES)
    full = values + INDEX_BYTES * model.nnz + tags
    original = original_bytes(q)
    return {"values_only": values, "with_indices": full, "original": original, "ratio_values": original / values, "ratio_indices": original / full}


def dense_tucker_bytes(ranks, dims) -> int:
    return VALUE_BYTES * int(np.prod(ranks) + sum(i * r for i, r in zip(dims, ranks)))


def on_disk(spark: SparkSession, path: str) -> int:
    """Bytes of the files under a path, by the binary file source (any file system that Spark reads)."""
    return int(spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).agg(F.sum("length")).first()[0] or 0)


def effective_dimension(model: FunctionalTucker) -> list[tuple[int, int]]:
    """(k, non-zeros of axis k)."""
    return [(k + 1, sum(len(f.coef) for f in fs)) for k, fs in enumerate(model.functions)]


def oscillation(samples: DataFrame) -> DataFrame:
    """k, j, sign_changes of each sampled vector (k, j, y, z)."""
    rows = samples.select("k", "j", F.posexplode("z").alias("i", "z")).where("z <> 0")
    w = Window.partitionBy("k", "j").orderBy("i")
    return rows.withColumn("turn", (F.col("z") * F.lag("z").over(w) < 0).cast("int")).groupBy("k", "j").agg(F.coalesce(F.sum("turn"), F.lit(0)).cast("long").alias("sign_changes"))


def report(points: DataFrame, model: FunctionalTucker, rate: float = 1.0) -> dict:
    """All that is known of a model against its points: errors at each stage, ranks, sizes, ratios."""
    err, spread, n = achieved_error(points, model, rate)
    q = model.meta.n_points or n
    return {"eps_requested": model.meta.eps_requested, "regrid_fraction": model.meta.regrid_fraction, "err_tensor": model.meta.err_tensor, "err_fit": model.meta.err_fit, "err_points": err, "err_points_2se": spread, "ranks": "x".join(map(str, model.ranks)), "core_entries": model.R, "nnz": model.nnz, **storage(model, q), "basis_evaluations": decode.basis_evaluations(model)}


def residual_regions(residuals: DataFrame, how: str = "cube", parts: int = 4):
    """Residual energy by coarse cells of the first three axes: cube, rollup or grouping sets (one axis at a time)."""
    cells = residuals.select(*[F.least(F.floor(F.col(c) * parts), F.lit(parts - 1)).cast("int").alias(f"b{k}") for k, c in enumerate(("c1", "c2", "c3"), 1)], (F.col("resid") * F.col("resid")).alias("e"))
    aggs = (F.sum("e").alias("energy"), F.count(F.lit(1)).alias("n"))
    if how == "cube":
        return cells.cube("b1", "b2", "b3").agg(*aggs)
    if how == "rollup":
        return cells.rollup("b1", "b2", "b3").agg(*aggs)
    b = [F.col(f"b{k}") for k in (1, 2, 3)]
    return cells.groupingSets([[b[0]], [b[1]], [b[2]]], *b).agg(*aggs)


def factor_table(samples: DataFrame, k: int = 1) -> DataFrame:
    """i and one column for each singular vector of axis k, for reading: a pivot of as many columns as the rank."""
    rows = samples.where(F.col("k") == k).select("j", F.posexplode("z").alias("i", "z"))
    return rows.groupBy("i").pivot("j").agg(F.first("z")).orderBy("i")
