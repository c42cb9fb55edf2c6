"""Deterministic sampling by hash: the same rows on any retry, partitioning or engine."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..schema import AxisSpec
from .axes import local


def hash_int(key: Column, seed: int | str = 0, part: int = 0) -> Column:
    """32 bits (of four parts) of the MD5 of key and seed, as a long; DuckDB gives the same. Parts of one hash in one projection cost one MD5."""
    return F.conv(F.substring(F.md5(F.concat(key.cast("string"), F.lit(f"/{seed}")).cast("binary")), 1 + 8 * part, 8), 16, 10).cast("long")


def hash01(key: Column, seed: int | str = 0) -> Column:
    return hash_int(key, seed) / F.lit(4294967296.0)


def hash01_sql(key: str, seed: int | str = 0) -> str:
    return f"(('0x' || substr(md5({key} || '/{seed}'), 1, 8))::BIGINT / 4294967296.0::DOUBLE)"


def hash_fraction(points: DataFrame, rate: float, seed: int | str = 0, key: str = "pt_key") -> DataFrame:
    """A share of the points; a filter fused with the scan."""
    return points if rate >= 1 else points.where(hash01(F.col(key), seed) < rate)


def capped_rate(q: int, n: int, support: float, rate: float = 0.1) -> float:
    """The rate that gives at most so many points a node: above that, more points cost time and add nothing."""
    return 0.0 if q == 0 else min(rate, 1.0, support * n / q)


def cell_of(axes: list[AxisSpec]) -> list[Column]:
    return [F.least(F.floor(local(F.col(f"c{k + 1}"), a)), F.lit(max(a.nodes - 2, 0))).cast("int").alias(f"i{k + 1}") for k, a in enumerate(axes)]


def stratified_by_cell(points: DataFrame, axes: list[AxisSpec], quota: int, seed: int | str = 0) -> DataFrame:
    """At most ``quota`` points of each grid cell, those of lowest hash. A ranking window by cell, of which Spark keeps only the quota before the shuffle."""
    cells = [f"i{k + 1}" for k in range(len(axes))]
    w = Window.partitionBy(*cells).orderBy("h", "pt_key")
    ranked = points.select("*", *cell_of(axes), hash_int(F.col("pt_key"), seed).alias("h")).withColumn("r", F.row_number().over(w))
    return ranked.where(F.col("r") <= quota).drop("r", "h", *cells)
