"""Axes: bounds, equispaced nodes, the map to the unit interval, dictionaries of categories."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schema import AXES, AxisSpec, coords


def fit_axes(points: DataFrame, nodes: list[int], bounds: list[tuple[float, float]] | None = None, names: list[str] | None = None, kinds: list[str] | None = None) -> list[AxisSpec]:
    """Axes over the points. Bounds that are not given are measured: one aggregate, one row to the driver."""
    cols = coords(len(nodes))
    if bounds is None:
        row = points.agg(*[f(c).alias(f"{n}{c}") for c in cols for f, n in ((F.min, "lo"), (F.max, "hi"))]).first()
        bounds = [(0.0 if row[f"lo{c}"] is None else row[f"lo{c}"], 1.0 if row[f"hi{c}"] is None else row[f"hi{c}"]) for c in cols]
    names, kinds = names or cols, kinds or ["space"] * len(cols)
    return [AxisSpec(n, float(lo), float(hi), m if hi > lo else 1, k) for n, (lo, hi), m, k in zip(names, bounds, nodes, kinds)]


#: Points of the regridded share for each node.
SUPPORT = 12


def nodes_for(q: int, weights: list[int], rate: float = 1.0, support: float = SUPPORT, least: int = 4) -> list[int]:
    """Nodes of each axis, in proportion to the weights, so that q * rate points give about ``support`` a node."""
    m = (max(q * rate, 1.0) / support / float(np.prod(weights))) ** (1 / len(weights))
    return [max(least, round(w * m)) for w in weights]


def unit_axes(nodes: list[int]) -> list[AxisSpec]:
    return [AxisSpec(c, 0.0, 1.0, m) for c, m in zip(coords(len(nodes)), nodes)]


def axes_table(spark: SparkSession, axes: list[AxisSpec]) -> DataFrame:
    return spark.createDataFrame([(k + 1, a.name, a.lo, a.hi, a.nodes, a.kind) for k, a in enumerate(axes)], AXES)


def node_table(spark: SparkSession, axes: list[AxisSpec]) -> DataFrame:
    """k, i, y: every node of every axis, made on the executors."""
    one = None
    for k, a in enumerate(axes):
        part = spark.range(a.nodes).select(F.lit(k + 1).alias("k"), F.col("id").cast("int").alias("i"), (F.lit(a.lo) + F.col("id") * F.lit(a.step)).alias("y"))
        one = part if one is None else one.unionByName(part)
    return one


def to_unit(c: Column, a: AxisSpec) -> Column:
    """The coordinate on [0, 1], clamped; 0 on an axis of one level."""
    if a.hi <= a.lo:
        return F.lit(0.0)
    return F.greatest(F.lit(0.0), F.least(F.lit(1.0), (c - F.lit(a.lo)) / F.lit(a.hi - a.lo)))


def local(c: Column, a: AxisSpec) -> Column:
    """The coordinate in steps of the grid."""
    return to_unit(c, a) * F.lit(float(max(a.nodes - 1, 0)))


def index_axis(df: DataFrame, column: str) -> DataFrame:
    """value, id: a sorted dictionary of a category, numbered from 0. Distinct values only meet in one task."""
    from pyspark.sql import Window

    distinct = df.select(F.col(column).alias("value")).where(F.col(column).isNotNull()).distinct()
    return distinct.select("value", (F.row_number().over(Window.orderBy("value")) - 1).cast("int").alias("id"))


def axis_kinds(df: DataFrame, columns: list[str], few: int = 256) -> DataFrame:
    """column, n_distinct (approximate), discrete: whether an axis has few levels."""
    row = df.agg(*[F.approx_count_distinct(c, 0.02).alias(c) for c in columns])
    return row.unpivot([], columns, "column", "n_distinct").withColumn("discrete", F.col("n_distinct") <= few)
