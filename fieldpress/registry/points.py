"""Queries on points, axes, sampling and regridding."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import axes as AX
from ..operators import regrid, sampling
from ..schema import FieldSpec, coords, indices
from ..sources import tables
from .base import hint, line, points_sql, q, qs, query

COARSE = AX.unit_axes([8, 8, 6])
_AFFINE = tables.AFFINE


@query(f"WITH {points_sql()} SELECT sum(CASE WHEN u IS NOT NULL AND c1 IS NOT NULL AND c2 IS NOT NULL AND c3 IS NOT NULL THEN 1 ELSE 0 END)::BIGINT AS kept, sum(CASE WHEN u IS NULL OR c1 IS NULL OR c2 IS NULL OR c3 IS NULL THEN 1 ELSE 0 END)::BIGINT AS n_null, sum(CASE WHEN isnan(u) THEN 1 ELSE 0 END)::BIGINT AS n_nan FROM p")
def clean_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    spec = FieldSpec({"day": tables.SHIP, "price": tables.PRICE, "quantity": tables.QUANTITY}, tables.FRONT3, tables.LINE_KEY)
    return tables.clean_counts(tables.table(spark, sf_dir, "lineitem"), spec)


@query(f"WITH {points_sql()} SELECT 1 AS k, min(c1) AS lo, max(c1) AS hi FROM p UNION ALL SELECT 2, min(c2), max(c2) FROM p UNION ALL SELECT 3, min(c3), max(c3) FROM p")
def axis_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    return AX.axes_table(spark, AX.fit_axes(line(spark, sf_dir), [8, 8, 6])).select("k", "lo", "hi")


@query(f"WITH {points_sql()}, a AS (SELECT 1 AS k, 10 AS n, min(c1) AS lo, max(c1) AS hi FROM p UNION ALL SELECT 2, 8, min(c2), max(c2) FROM p UNION ALL SELECT 3, 6, min(c3), max(c3) FROM p) SELECT k, i::INTEGER AS i, {qs('lo + i * ((hi - lo) / (n - 1.0::DOUBLE))', 9)} AS y FROM (SELECT *, unnest(range(n)) AS i FROM a)")
def axis_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every node of axes between the bounds of the points."""
    return AX.node_table(spark, AX.fit_axes(line(spark, sf_dir), [10, 8, 6])).select("k", "i", q("y", 9).alias("y"))


@query(f"WITH {points_sql()} SELECT pt_key, {qs('c1')} AS c1, {qs('c2')} AS c2, {qs('c3')} AS c3 FROM p")
def unit_coordinates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line(spark, sf_dir).select("pt_key", *[q(c).alias(c) for c in coords(3)])


@query(f"WITH {points_sql()} SELECT pt_key, {qs('u')} AS u FROM p")
def planted_field(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line(spark, sf_dir).select("pt_key", q("u").alias("u"))


@query(f"WITH {points_sql()} SELECT pt_key, {hint('pt_key', 0)} AS h FROM p WHERE {hint('pt_key', 0)} / 4294967296.0::DOUBLE < 0.1::DOUBLE")
def hash_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sampling.hash_fraction(line(spark, sf_dir), 0.1).select("pt_key", sampling.hash_int(F.col("pt_key")).alias("h"))


@query(f"WITH {points_sql()}, r AS (SELECT least(0.1::DOUBLE, 2.0::DOUBLE * 384 / count(*)) AS rate FROM p) SELECT count(*)::BIGINT AS n, {qs('max(rate)', 9)} AS rate FROM p, r WHERE {hint('pt_key', 0)} / 4294967296.0::DOUBLE < rate")
def capped_rate_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = line(spark, sf_dir)
    rate = sampling.capped_rate(points.count(), 384, 2.0)
    return sampling.hash_fraction(points, rate).agg(F.count(F.lit(1)).alias("n"), q(F.lit(rate), 9).alias("rate"))


@query(f"WITH {points_sql()} SELECT pt_key FROM (SELECT pt_key, row_number() OVER (PARTITION BY least(floor(c1 * 7), 6), least(floor(c2 * 7), 6), least(floor(c3 * 5), 4) ORDER BY {hint('pt_key', 3)}, pt_key) AS r FROM p) WHERE r <= 2")
def stratified_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sampling.stratified_by_cell(line(spark, sf_dir), COARSE, 2, 3).select("pt_key")


@query(f"WITH {points_sql()} SELECT floor(c1 * 7 + 0.5)::INTEGER AS i1, floor(c2 * 7 + 0.5)::INTEGER AS i2, floor(c3 * 5 + 0.5)::INTEGER AS i3, {qs('avg(u)')} AS v, count(*)::DOUBLE AS support FROM p GROUP BY 1, 2, 3")
def regrid_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return regrid.nearest(line(spark, sf_dir), COARSE).select(*indices(3), q("v").alias("v"), "support")


def corners_sql(source: str = "p", n: tuple[int, ...] = (8, 8, 6)) -> str:
    t = ", ".join(f"c{k} * {m - 1}.0::DOUBLE AS t{k}, least(floor(c{k} * {m - 1}.0::DOUBLE), {m - 2})::INTEGER AS b{k}" for k, m in enumerate(n, 1))
    w = " * ".join(f"(CASE WHEN e{k} = 1 THEN t{k} - b{k} ELSE 1.0::DOUBLE - (t{k} - b{k}) END)" for k in range(1, len(n) + 1))
    es = ", ".join(f"(VALUES (0), (1)) x{k}(e{k})" for k in range(1, len(n) + 1))
    idx = ", ".join(f"b{k} + e{k} AS i{k}" for k in range(1, len(n) + 1))
    return f"cells AS (SELECT u, {t} FROM {source}), corners AS (SELECT * FROM (SELECT {idx}, {w} AS w, u, {', '.join(f't{k} - (b{k} + e{k}) AS a{k}' for k in range(1, len(n) + 1))} FROM cells, {es}) WHERE w > 0)"


@query(f"WITH {points_sql()}, {corners_sql()} SELECT i1, i2, i3, {qs('sum(w * u) / sum(w)')} AS v, {qs('sum(w)')} AS support FROM corners GROUP BY ALL".replace("GROUP BY ALL", "GROUP BY i1, i2, i3"))
def regrid_tent(spark: SparkSession, sf_dir: str) -> DataFrame:
    return regrid.tent_average(line(spark, sf_dir), COARSE).select(*indices(3), q("v").alias("v"), q("support").alias("support"))


def saw_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """part's price, a sawtooth over the key, on one unit axis."""
    part = tables.table(spark, sf_dir, "part").select("p_partkey", "p_retailprice")
    n = part.count()
    return part.select(F.col("p_partkey").cast("string").alias("pt_key"), (F.col("p_partkey") / F.lit(float(max(n - 1, 1)))).alias("c1"), F.col("p_retailprice").alias("u"))


SAW = "p AS (SELECT p_partkey::VARCHAR AS pt_key, p_partkey / (SELECT greatest(count(*) - 1, 1)::DOUBLE FROM part) AS c1, p_retailprice AS u FROM part)"


@query(f"WITH {SAW}, {corners_sql('p', (9,))}, m AS (SELECT i1, sum(w) AS s0, sum(w * a1) AS s1, sum(w * a1 * a1) AS s2, sum(w * u) AS t0, sum(w * a1 * u) AS t1 FROM corners GROUP BY i1) SELECT i1, {qs('(t0 * s2 - t1 * s1) / (s0 * s2 - s1 * s1)', 4)} AS v FROM m")
def regrid_linear_1d(spark: SparkSession, sf_dir: str) -> DataFrame:
    return regrid.local_linear(saw_points(spark, sf_dir), AX.unit_axes([9]), ridge=0.0, adaptive=False).select("i1", q("v", 4).alias("v"))


@query("SELECT i1::INTEGER AS i1, i2::INTEGER AS i2, i3::INTEGER AS i3, " + qs("1 + 2 * i1 / 3.0::DOUBLE - 3 * i2 / 3.0::DOUBLE + 0.5::DOUBLE * i3 / 2.0::DOUBLE", 4) + " AS v FROM unnest(range(4)) a(i1), unnest(range(4)) b(i2), unnest(range(3)) c(i3)")
def regrid_linear_affine_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = regrid.local_linear(line(spark, sf_dir, _AFFINE), AX.unit_axes([4, 4, 3]), ridge=0.0, adaptive=False)
    return t.select(*indices(3), q("v", 4).alias("v"))


_FINE = "s AS (SELECT * FROM p WHERE " + hint("pt_key", 0) + " / 4294967296.0::DOUBLE < 100 / (SELECT count(*) FROM p)::DOUBLE)"


def _thin(spark: SparkSession, sf_dir: str) -> DataFrame:
    """About a hundred points for 384 nodes, whatever the table's size: some nodes stay uncovered."""
    points = line(spark, sf_dir)
    return regrid.tent_average(sampling.hash_fraction(points, 100 / points.count()), COARSE)


@query(f"WITH {points_sql()}, {_FINE}, {corners_sql('s')}, t AS (SELECT i1, i2, i3, sum(w) AS s FROM corners GROUP BY i1, i2, i3) SELECT 384::BIGINT AS nodes, count(*)::BIGINT AS touched, {qs('min(s)', 9)} AS min_support, {qs('1 - count(*) / 384.0::DOUBLE', 9)} AS hole_fraction FROM t")
def regrid_coverage(spark: SparkSession, sf_dir: str) -> DataFrame:
    return regrid.coverage(_thin(spark, sf_dir), COARSE).select("nodes", "touched", q("min_support", 9).alias("min_support"), q("hole_fraction", 9).alias("hole_fraction"))


_ALL = "(SELECT i1::INTEGER AS i1, i2::INTEGER AS i2, i3::INTEGER AS i3 FROM unnest(range(8)) a(i1), unnest(range(8)) b(i2), unnest(range(6)) c(i3))"


@query(f"WITH {points_sql()}, {_FINE}, {corners_sql('s')} SELECT g.i1, g.i2, g.i3 FROM {_ALL} g ANTI JOIN corners t ON g.i1 = t.i1 AND g.i2 = t.i2 AND g.i3 = t.i3")
def regrid_holes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return regrid.holes(_thin(spark, sf_dir), COARSE)


@query(
    f"WITH {points_sql()}, {_FINE}, {corners_sql('s')}, t AS (SELECT i1, i2, i3, sum(w * u) / sum(w) AS v FROM corners GROUP BY i1, i2, i3), "
    f"h AS (SELECT g.* FROM {_ALL} g ANTI JOIN t ON g.i1 = t.i1 AND g.i2 = t.i2 AND g.i3 = t.i3) "
    f"SELECT h.i1, h.i2, h.i3, {qs('avg(t.v)')} AS v FROM h JOIN t ON abs(h.i1 - t.i1) + abs(h.i2 - t.i2) + abs(h.i3 - t.i3) = 1 GROUP BY h.i1, h.i2, h.i3"
)
def fill_holes_once(spark: SparkSession, sf_dir: str) -> DataFrame:
    return regrid.fill_once(_thin(spark, sf_dir), COARSE).where("filled").select(*indices(3), q("v").alias("v"))


@query("SELECT 384::BIGINT AS nodes, true AS complete")
def fill_holes_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = regrid.fill_holes(_thin(spark, sf_dir), COARSE)
    return t.agg(F.count(F.lit(1)).alias("nodes"), (F.count("v") == 384).alias("complete"))


CUBE_AXES = AX.unit_axes([101, 50, 11])


def revenue_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem as cells of 25-day bucket, quantity and discount with the price as measure."""
    day = F.expr("datediff(l_shipdate, DATE'1995-01-01')")
    return tables.table(spark, sf_dir, "lineitem").select(F.greatest(F.lit(0), F.least(F.lit(100), F.floor(day / 25))).cast("int").alias("i1"), (F.col("l_quantity") - 1).cast("int").alias("i2"), F.floor(F.col("l_discount") * 100 + 0.5).cast("int").alias("i3"), F.col("l_extendedprice").alias("v"))


REVENUE = "cells AS (SELECT greatest(0, least(100, floor(date_diff('day', DATE '1995-01-01', l_shipdate::DATE) / 25.0)))::INTEGER AS i1, (l_quantity - 1)::INTEGER AS i2, floor(l_discount * 100 + 0.5)::INTEGER AS i3, l_extendedprice AS v FROM lineitem)"


@query(
    f"WITH {REVENUE}, g AS (SELECT x.i1, x.i2, x.i3, coalesce(y.v, 0) AS v FROM (SELECT i1::INTEGER AS i1, i2::INTEGER AS i2, i3::INTEGER AS i3 FROM unnest(range(101)) a(i1), unnest(range(50)) b(i2), unnest(range(11)) c(i3)) x "
    "LEFT JOIN (SELECT i1, i2, i3, sum(v) AS v FROM cells GROUP BY i1, i2, i3) y ON x.i1 = y.i1 AND x.i2 = y.i2 AND x.i3 = y.i3), "
    "a AS (SELECT i1, i2, i3, sum(v) OVER (PARTITION BY i2, i3 ORDER BY i1) AS v FROM g), b AS (SELECT i1, i2, i3, sum(v) OVER (PARTITION BY i1, i3 ORDER BY i2) AS v FROM a) "
    f"SELECT i1, i2, i3, {qs('sum(v) OVER (PARTITION BY i1, i2 ORDER BY i3)', 2)} AS v FROM b"
)
def cumulative_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    return regrid.cumulative_cube(revenue_cells(spark, sf_dir), CUBE_AXES).select(*indices(3), q("v", 2).alias("v"))


@query("SELECT id::INTEGER AS id, value FROM (SELECT value, row_number() OVER (ORDER BY value) - 1 AS id FROM (SELECT DISTINCT lang AS value FROM documents WHERE lang IS NOT NULL))")
def axis_dictionary(spark: SparkSession, sf_dir: str) -> DataFrame:
    return AX.index_axis(tables.table(spark, sf_dir, "documents"), "lang")


@query("SELECT 'l_discount' AS \"column\", true AS discrete UNION ALL SELECT 'l_quantity', true UNION ALL SELECT 'l_extendedprice', count(DISTINCT l_extendedprice) <= 256 FROM lineitem")
def axis_kinds(spark: SparkSession, sf_dir: str) -> DataFrame:
    return AX.axis_kinds(tables.table(spark, sf_dir, "lineitem"), ["l_discount", "l_quantity", "l_extendedprice"]).select("column", "discrete")


@query(f"WITH {points_sql('0e0')} SELECT var, count(*)::BIGINT AS n, {qs('sum(u)', 2)} AS total FROM (" + " UNION ALL ".join(f"SELECT '{n}' AS var, {e} AS u FROM p" for n, e in tables.ELEVEN.items()) + ") GROUP BY var")
def eleven_fields(spark: SparkSession, sf_dir: str) -> DataFrame:
    wide = tables.line_points_multi(spark, sf_dir)
    return tables.wide_to_long(wide, list(tables.ELEVEN), 3).groupBy("var").agg(F.count(F.lit(1)).alias("n"), q(F.sum("u"), 2).alias("total"))


