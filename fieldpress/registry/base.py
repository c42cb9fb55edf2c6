"""Registration, shared fixtures, and the rounding that both engines agree on."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.axes import nodes_for, unit_axes
from ..plans.compress import compress
from ..plans.model import FunctionalTucker
from ..schema import AxisSpec
from ..sources import tables

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return add


def q(c: Column | str, k: int = 6) -> Column:
    """Rounded to k decimals the same way in both engines; no negative zero."""
    c = F.col(c) if isinstance(c, str) else c
    return F.floor(c * F.lit(float(10**k)) + 0.5) / F.lit(float(10**k))


def qs(e: str, k: int = 6) -> str:
    return f"(floor(({e}) * 1e{k} + 0.5::DOUBLE)::BIGINT / 1e{k})"


def hint(key: str, seed: int | str, part: int = 0) -> str:
    """The 32-bit hash of ``sampling.hash_int`` in SQL."""
    return f"('0x' || substr(md5({key} || '/{seed}'), {1 + 8 * part}, 8))::BIGINT"


def line(spark: SparkSession, sf_dir: str, value: str = tables.FRONT3) -> DataFrame:
    return tables.line_points(spark, sf_dir, value)


def points_sql(value: str = tables.FRONT3) -> str:
    return f"p AS (SELECT pt_key, c1, c2, c3, {value} AS u FROM ({tables.POINTS_SQL}))"


#: One set of parameters for tables of any size: the grids follow the number of points (``axes.nodes_for``).
EPS = 1e-2
RATE = 0.1
WEIGHTS3, WEIGHTS4 = [2, 2, 1], [1, 1, 1, 1]


def grid3(q: int, rate: float = 1.0) -> list[AxisSpec]:
    return unit_axes(nodes_for(q, WEIGHTS3, rate))


def model3(spark: SparkSession, sf_dir: str, eps: float | None = EPS, value: str = tables.FRONT3, rate: float = 1.0, **kw) -> FunctionalTucker:
    points = line(spark, sf_dir, value)
    q = points.count()
    return compress(points, grid3(q, rate), eps, rate, n_points=q, **kw)


def model4(spark: SparkSession, sf_dir: str, eps: float | None = EPS, rate: float = 1.0, **kw) -> FunctionalTucker:
    points = tables.order_points(spark, sf_dir)
    q = points.count()
    return compress(points, unit_axes(nodes_for(q, WEIGHTS4, rate)), eps, rate, n_points=q, **kw)


def rows(spark: SparkSession, data: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(data, schema)
