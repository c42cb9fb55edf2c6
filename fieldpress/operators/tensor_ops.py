"""Tensors as rows (i1..id, v): fibers, Gram matrices, mode products, norms.

A fiber is the vector along one axis; fibers are gathered by the other indices (one
shuffle), multiplied in Arrow batches as matrices, and partial Gram matrices are summed by
entry, so only I x I numbers reach the driver. The relational forms say the same in joins.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..schema import indices, tensor_schema


def rest_id(dims: list[int], k: int) -> Column:
    """All indices but the k-th as one number (row-major)."""
    out: Column = F.lit(0).cast("long")
    for m, n in enumerate(dims):
        if m != k:
            out = out * F.lit(n) + F.col(f"i{m + 1}")
    return out


def fibers(tensor: DataFrame, dims: list[int], k: int) -> DataFrame:
    """rest, vec: the fibers along axis k; missing entries are 0. A fiber has I_k entries at most, so a group is bounded."""
    pairs = F.sort_array(F.collect_list(F.struct(F.col(f"i{k + 1}").alias("i"), "v")))
    rows = tensor.select(rest_id(dims, k).alias("rest"), f"i{k + 1}", "v").groupBy("rest").agg(pairs.alias("p"))
    n = dims[k]
    dense = F.when(F.size("p") == n, F.transform("p", lambda x: x["v"])).otherwise(F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: F.coalesce(F.element_at(F.map_from_entries("p"), i), F.lit(0.0))))
    return rows.select("rest", dense.alias("vec"))


def _matrix(batch: pa.RecordBatch, n: int) -> np.ndarray:
    return batch.column("vec").flatten().to_numpy(zero_copy_only=False).reshape(-1, n)


def partial_grams(vectors: DataFrame, n: int) -> DataFrame:
    """a, b, g (a <= b): Gram entries summed over all fibers; each task adds up its own before the shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for batch in batches:
            if batch.num_rows:
                m = _matrix(batch, n)
                total = m.T @ m if total is None else total + m.T @ m
        if total is not None:
            a, b = np.triu_indices(n)
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int32()), pa.array(b, pa.int32()), pa.array(total[a, b])], names=["a", "b", "g"])

    return vectors.select("vec").mapInArrow(run, "a int, b int, g double").groupBy("a", "b").agg(F.sum("g").alias("g"))


def gram(vectors: DataFrame, n: int) -> np.ndarray:
    """The I x I Gram matrix on the driver."""
    out = np.zeros((n, n))
    for r in partial_grams(vectors, n).collect():
        out[r.a, r.b] = out[r.b, r.a] = r.g
    return out


def gram_sql(tensor: DataFrame, dims: list[int], k: int) -> DataFrame:
    """a, b, g by a self-join on the other indices."""
    x = tensor.select(rest_id(dims, k).alias("rest"), F.col(f"i{k + 1}").alias("a"), F.col("v").alias("va"))
    y = x.select(F.col("rest"), F.col("a").alias("b"), F.col("va").alias("vb"))
    return x.join(y, "rest").where("a <= b").groupBy("a", "b").agg(F.sum(F.col("va") * F.col("vb")).alias("g"))


def multiply_fibers(vectors: DataFrame, matrix: np.ndarray) -> DataFrame:
    """Every fiber times a small matrix (rows: I_k): rest, vec of matrix.shape[1]. No shuffle."""
    n, r = matrix.shape

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = _matrix(batch, n) @ matrix
            flat = pa.array(out.ravel())
            yield pa.RecordBatch.from_arrays([batch.column("rest"), pa.ListArray.from_arrays(pa.array(np.arange(len(out) + 1) * r, pa.int32()), flat)], names=["rest", "vec"])

    return vectors.select("rest", "vec").mapInArrow(run, "rest long, vec array<double>")


def unfiber(vectors: DataFrame, dims: list[int], k: int) -> DataFrame:
    """Back to rows; dims has the new size of axis k."""
    rows = vectors.select("rest", F.posexplode("vec").alias("i", "v"))
    cols, rest = {}, F.col("rest")
    for m in reversed(range(len(dims))):
        if m != k:
            cols[m] = F.pmod(rest, F.lit(dims[m])).cast("int").alias(f"i{m + 1}")
            rest = F.floor(rest / F.lit(dims[m]))
    cols[k] = F.col("i").alias(f"i{k + 1}")
    return rows.select(*[cols[m] for m in range(len(dims))], "v")


def mode_product(tensor: DataFrame, dims: list[int], matrix: np.ndarray, k: int) -> DataFrame:
    """Contract axis k with the rows of a matrix: its size becomes matrix.shape[1]."""
    new = [matrix.shape[1] if m == k else n for m, n in enumerate(dims)]
    return unfiber(multiply_fibers(fibers(tensor, dims, k), matrix), new, k)


def mode_product_sql(tensor: DataFrame, factor: DataFrame, k: int, d: int) -> DataFrame:
    """The same by a join with factor (i, j, w), which is broadcast: it has I_k x r_k rows."""
    others = [i for m, i in enumerate(indices(d)) if m != k]
    me = f"i{k + 1}"
    out = tensor.join(F.broadcast(factor), F.col(me) == F.col("i")).groupBy(*others, "j").agg(F.sum(F.col("v") * F.col("w")).alias("v"))
    return out.select(*[F.col("j").alias(me) if m == k else F.col(i) for m, i in enumerate(indices(d))], "v")


def norm2(tensor: DataFrame) -> float:
    return float(tensor.agg(F.sum(F.col("v") * F.col("v"))).first()[0] or 0.0)


def inner(coefs: DataFrame, basis_rows: DataFrame, d: int) -> DataFrame:
    """Inner product of a coefficient tensor (i1..id, v) with each point's basis values (pt_key, i1..id, b): pt_key, value."""
    return basis_rows.join(coefs, indices(d)).groupBy("pt_key").agg(F.sum(F.col("v") * F.col("b")).alias("value"))


def to_numpy(tensor: DataFrame, dims: list[int]) -> np.ndarray:
    """The dense tensor on the driver; for sizes that the caller has checked."""
    out = np.zeros(dims)
    pdf = tensor.select(*indices(len(dims)), "v").toPandas()
    out[tuple(pdf[i].to_numpy() for i in indices(len(dims)))] = pdf["v"].to_numpy()
    return out


def from_numpy(spark, array: np.ndarray) -> DataFrame:
    idx = np.indices(array.shape).reshape(array.ndim, -1)
    cols = [pa.array(x, pa.int32()) for x in idx] + [pa.array(array.ravel().astype(float))]
    return spark.createDataFrame(pa.Table.from_arrays(cols, names=[*indices(array.ndim), "v"])).select(*[F.col(f.name).cast(f.dataType).alias(f.name) for f in tensor_schema(array.ndim)])
