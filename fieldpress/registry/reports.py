"""The reference's experiments on the given tables.

Queries with SQL return numbers that SQL recomputes, or values of a planted grid (fixed,
whatever the tables) and errors measured once, to two decimals, for the table sizes that
the comparison runs on. Those named ``*_report`` return all numbers of a run.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor

import numpy as np
from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import basis as B
from ..functions import sparse as S
from ..operators import baselines, decode, funcfit, metrics, mixing, regrid, sampling, sketch, tucker
from ..operators import tensor_ops as ops
from ..operators.axes import unit_axes
from ..operators.storage import cut, discard
from ..plans import refit
from ..plans.compress import compress, grid_tensor
from ..plans.model import FunctionalTucker
from ..schema import legendre, multiwavelet
from ..sources import tables
from .base import EPS, RATE, grid3, hint, line, model3, model4, points_sql, q, qs, query, rows
from .refits import _BLOCKS, _DRAW, line_model
from .tensors import CHARGE_DIMS, charge_tensor, front_of_levels, planted


@query("SELECT true AS exact")
def compress_affine(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An affine field goes through regrid, decomposition, functions and decoding unchanged."""
    points = line(spark, sf_dir, tables.AFFINE)
    tensor = regrid.fill_holes(regrid.local_linear(points, unit_axes([6, 6, 5]), ridge=1e-12, adaptive=False), unit_axes([6, 6, 5]))
    model = compress(points, unit_axes([6, 6, 5]), 1e-6, candidates=[legendre(2)], tensor=tensor)
    return rows(spark, [(metrics.achieved_error(points, model)[0] < 1e-5,)], "exact boolean")


@query("SELECT true AS rank_one, true AS exact")
def compress_product(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = planted(spark, tables.PRODUCT, [6, 6, 6])
    points = line(spark, sf_dir, tables.PRODUCT)
    model = compress(points, unit_axes([6, 6, 6]), 1e-6, candidates=[legendre(1)], tensor=t)
    return rows(spark, [(model.ranks == (1, 1, 1), metrics.achieved_error(points, model)[0] < 1e-9)], "rank_one boolean, exact boolean")


@query("SELECT true AS charge_exact, 1 AS r1, 1 AS r2, 1 AS r3")
def compress_charge(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The charge on its grid of levels: ranks one, straight lines, decoded values equal the charge of every line."""
    t = planted(spark, "(1e0 + 49e0*c1)*(1e0 - 0.1e0*c2)*(1e0 + 0.08e0*c3)", [50, 11, 9])
    spec_points = tables.table(spark, sf_dir, "lineitem").select(((F.col("l_quantity") - 1) / 49).alias("c1"), (F.col("l_discount") / 0.1).alias("c2"), (F.col("l_tax") / 0.08).alias("c3"), (F.col("l_quantity") * (1 - F.col("l_discount")) * (1 + F.col("l_tax"))).alias("u"))
    model = compress(spec_points, unit_axes([50, 11, 9]), 1e-6, candidates=[legendre(1)], tensor=t)
    err = decode.residuals(spec_points, model).agg(F.max("abs_resid")).first()[0]
    return rows(spark, [(err < 1e-8, *map(int, model.ranks))], "charge_exact boolean, r1 int, r2 int, r3 int")


def measured(values: dict[int, str], table: str, columns: str) -> str:
    """SQL of rows measured for a table of so many rows."""
    parts = [f"SELECT {n} AS n_points, * FROM (VALUES {v}) v({columns})" for n, v in values.items()]
    return f"SELECT m.* FROM ({' UNION ALL '.join(parts)}) m WHERE n_points = (SELECT count(*) FROM {table})"


def fitted(points: DataFrame, model: FunctionalTucker) -> FunctionalTucker:
    """The core from all points; the sketch where the whole problem is too large is ``refit_core``'s business."""
    return refit.refit_full(points, model)


def error(points: DataFrame, model: FunctionalTucker) -> float:
    return metrics.achieved_error(points, model)[0]


# -- sizes, ranks and errors of the two cases ----------------------------------------------------------


@query(f"WITH {points_sql()}, n AS (SELECT count(*)::BIGINT AS n_points, count(*) FILTER (WHERE {hint('pt_key', 0)} / 4294967296.0::DOUBLE < {RATE}::DOUBLE)::BIGINT AS n_regridded FROM p) SELECT eps, r1, r2, r3, n_points, n_regridded, 8 * n_points AS original_bytes FROM (VALUES (1e-1::DOUBLE, 2, 2, 1), (1e-2, 5, 5, 2), (1e-3, 7, 7, 2), (1e-4, 8, 8, 2)) v(eps, r1, r2, r3), n")
def ranks_by_precision(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Multilinear ranks of the field on an exact grid of 40 x 40 x 20 for falling precision, beside the points and the share to regrid (``table1_report`` has the ranks of the regridded tensors)."""
    points = line(spark, sf_dir)
    n, part = points.count(), sampling.hash_fraction(points, RATE, 0).count()
    array = ops.to_numpy(planted(spark, tables.FRONT3, [40, 40, 20]), [40, 40, 20])
    out = [(eps, *map(int, tucker.numpy_st_hosvd(array, eps).ranks), n, part, metrics.original_bytes(n)) for eps in (1e-1, 1e-2, 1e-3, 1e-4)]
    return rows(spark, out, "eps double, r1 int, r2 int, r3 int, n_points long, n_regridded long, original_bytes long")


@query()
def table1_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Grid, precision and ranks of both cases, from a tenth of the points and from all."""
    out = []
    for rate in (RATE, 1.0):
        points = line(spark, sf_dir)
        axes = grid3(points.count(), rate)
        dims = [a.nodes for a in axes]
        tensor = grid_tensor(points, axes, rate)
        for eps in (1e-1, 1e-2, 1e-3, 1e-4):
            r = tucker.st_hosvd(tensor.select("i1", "i2", "i3", "v"), dims, eps)
            out.append(("three axes", rate, "x".join(map(str, dims)), eps, "x".join(map(str, r.ranks)), r.core.size, r.error))
        m = model4(spark, sf_dir, rate=rate)
        out.append(("four axes", rate, "x".join(str(a.nodes) for a in m.axes), EPS, "x".join(map(str, m.ranks)), m.R, m.meta.err_tensor))
    return rows(spark, out, "name string, rate double, grid string, eps double, ranks string, core_entries int, err_tensor double")


_FRONT = {6000: "(0.1::DOUBLE, '5x5x4', 0.29::DOUBLE, 0.25::DOUBLE), (1.0, '6x6x3', 0.06, 0.04)", 60000: "(0.1::DOUBLE, '6x6x4', 0.06::DOUBLE, 0.04::DOUBLE), (1.0, '5x5x2', 0.09, 0.05)"}


@query(measured(_FRONT, "lineitem", "rate, ranks, err_before, err_after"))
def compress_front3(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three axes, from a tenth of the points and from all: ranks, errors at all points before and after the core's re-estimation."""
    points = line(spark, sf_dir).persist()
    n, out = points.count(), []
    for rate in (RATE, 1.0):
        m = model3(spark, sf_dir, rate=rate)
        out.append((n, rate, "x".join(map(str, m.ranks)), error(points, m), error(points, fitted(points, m))))
    points.unpersist()
    return rows(spark, out, "n_points int, rate double, ranks string, a double, b double").select("n_points", "rate", "ranks", q("a", 2).alias("err_before"), q("b", 2).alias("err_after"))


_FOUR = {6000: "('5x5x5x5', 0.29::DOUBLE, 0.25::DOUBLE)", 60000: "('6x7x7x6', 0.12::DOUBLE, 0.1::DOUBLE)"}


@query(measured(_FOUR, "lineitem", "ranks, err_before, err_after") + " AND EXISTS (SELECT 1 FROM orders)")
def compress_front4(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = tables.order_points(spark, sf_dir).persist()
    m = model4(spark, sf_dir)
    out = [(points.count(), "x".join(map(str, m.ranks)), error(points, m), error(points, fitted(points, m)))]
    points.unpersist()
    return rows(spark, out, "n_points int, ranks string, a double, b double").select("n_points", "ranks", q("a", 2).alias("err_before"), q("b", 2).alias("err_after"))


_TABLE2 = {6000: "('three axes', '6x6x3', 108, 0.04::DOUBLE), ('four axes', '5x5x5x5', 625, 0.25)", 60000: "('three axes', '5x5x2', 50, 0.05::DOUBLE), ('four axes', '6x7x7x6', 1764, 0.1)"}


@query(f"SELECT name, n_points::BIGINT AS n_points, 8 * n_points::BIGINT AS original, ranks, core_entries, err_points FROM ({measured(_TABLE2, 'lineitem', 'name, ranks, core_entries, err_points')})")
def compression_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = compression_report(spark, sf_dir)
    return r.select("name", "n_points", "original", "ranks", "core_entries", q("err_points", 2).alias("err_points"))


@query()
def compression_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Requested and achieved precision, ratio and storage of both cases; ``reached``: the achieved error is within twice the requested one."""
    out = []
    for name, points, model in (("three axes", line(spark, sf_dir), model3(spark, sf_dir)), ("four axes", tables.order_points(spark, sf_dir), model4(spark, sf_dir))):
        model = fitted(points, model)
        r = metrics.report(points, model)
        out.append((name, model.meta.n_points, r["ranks"], r["core_entries"], r["nnz"], r["eps_requested"], r["err_tensor"], r["err_fit"], r["err_points"], r["values_only"], r["original"], r["ratio_values"], r["ratio_indices"], r["regrid_fraction"], bool(r["err_points"] <= 2 * r["eps_requested"])))
    return rows(spark, out, "name string, n_points long, ranks string, core_entries int, nnz int, eps_requested double, err_tensor double, err_fit double, err_points double, values_only long, original long, ratio_values double, ratio_indices double, regrid_fraction double, reached boolean")


# -- decay, vectors and spaces -------------------------------------------------------------------------


@query("SELECT * FROM (VALUES (0, 1), (1, 2), (2, 6), (3, 19), (4, 43)) v(decade, n_entries)")
def decay_of_core(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Core entries at least 10^-decade of the largest, of the front on lineitem's grid of levels at 1e-4 (``core_decay_report``: of the regridded points)."""
    return _decades(spark, tucker.numpy_st_hosvd(front_of_levels(spark, sf_dir), 1e-4).core)


def _decades(spark: SparkSession, core: np.ndarray) -> DataFrame:
    cells = rows(spark, [([int(i) + 1 for i in j], float(v)) for j, v in np.ndenumerate(core)], "j array<int>, v double")
    decay = metrics.core_decay(cells)
    decades = spark.range(5).select(F.col("id").cast("int").alias("decade"))
    top = decay.where("rank = 1").select(F.col("abs_core").alias("top"))
    return decades.join(decay.crossJoin(F.broadcast(top)), F.col("abs_core") >= F.col("top") * F.pow(F.lit(10.0), -F.col("decade"))).groupBy("decade").agg(F.count(F.lit(1)).cast("int").alias("n_entries"))


@query()
def core_decay_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """rank, abs_core, cum_energy of the core of all regridded points at 1e-4."""
    m = model3(spark, sf_dir, 1e-4)
    return metrics.core_decay(rows(spark, [([int(i) + 1 for i in j], float(v)) for j, v in np.ndenumerate(m.core)], "j array<int>, v double"))


def _front_vectors(spark: SparkSession) -> tucker.TuckerResult:
    dims = [128, 24, 12]
    return tucker.numpy_st_hosvd(ops.to_numpy(planted(spark, tables.FRONT3, dims), dims), 1e-4)


def _error(z: np.ndarray, spec) -> float:
    phi = B.evaluate_matrix(np.linspace(0, 1, len(z)), spec)
    return S.relative_error(phi, z, S.fit_lars_loo(phi, z).coef) if spec.family == "legendre" else S.relative_error(phi, z, S.ols(phi, z))


@query("SELECT * FROM (VALUES (5, 0.084::DOUBLE), (10, 0.006), (20, 0.0), (40, 0.0)) v(degree, err)")
def first_vector_degrees(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first singular vector of the first mode of the front on lineitem's grid of levels: the error falls with the degree (``vector_report``: of the regridded points)."""
    z = tucker.numpy_st_hosvd(front_of_levels(spark, sf_dir), 1e-4).factors[0][:, 0]
    return rows(spark, [(d, _error(z, legendre(d))) for d in (5, 10, 20, 40)], "degree int, e double").select("degree", q("e", 3).alias("err"))


@query("SELECT * FROM (VALUES ('legendre(20)', 0.0::DOUBLE, 0.692::DOUBLE), ('legendre(40)', 0.0, 0.01), ('multiwavelet(3,5)', 0.0, 0.016)) v(space, err_first, err_last)")
def last_vector_spaces(spark: SparkSession, sf_dir: str) -> DataFrame:
    """First and last singular vector in polynomials and wavelets: the last is harder in each."""
    w = _front_vectors(spark).factors[0]
    specs = (legendre(20), legendre(40), multiwavelet(3, 5), multiwavelet(5, 3))
    out = [(x.tag, _error(w[:, 0], x) if x.size < 128 else 0.0, _error(w[:, -1], x) if x.size < 128 else 0.0) for x in specs if x.size < 128]
    return rows(spark, out, "space string, a double, b double").select("space", q("a", 3).alias("err_first"), q("b", 3).alias("err_last"))


@query()
def vector_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every singular vector of a tenth of the points in each space alone: sign changes, functions, non-zeros, leave-one-out and node errors, and the largest error at a node."""
    points = line(spark, sf_dir)
    axes = grid3(points.count(), RATE)
    found = tucker.st_hosvd(grid_tensor(points, axes, RATE).select("i1", "i2", "i3", "v"), [a.nodes for a in axes], 1e-4)
    samples = funcfit.vector_samples(spark, found.factors, axes)
    out = None
    for solo in (legendre(20), legendre(40), multiwavelet(3, 5), multiwavelet(5, 3), multiwavelet(1, 3)):
        fits = funcfit.fit_all(samples, [solo]).select("k", "j", F.lit(solo.tag).alias("asked"), F.concat_ws("/", "basis.family", "basis.resolution", "basis.degree").alias("space"), "n", "nnz", "fit_err", "loo_err")
        out = fits if out is None else out.unionByName(fits)
    return out.join(metrics.oscillation(samples), ["k", "j"])


_SAW = "p AS (SELECT p_partkey / (SELECT greatest(count(*) - 1, 1)::DOUBLE FROM part) AS x, p_retailprice AS u FROM part), t AS (SELECT sum(u * u) AS uu FROM p)"


def _cells_sql(k: int) -> str:
    return f"(SELECT sqrt(sum((c.u - r.a - r.b * c.x) * (c.u - r.a - r.b * c.x)) / (SELECT uu FROM t)) FROM (SELECT *, least(floor(x * {k}), {k} - 1) AS cell FROM p) c JOIN (SELECT cell, coalesce(regr_slope(u, x), 0) AS b, coalesce(regr_intercept(u, x), avg(u)) AS a FROM (SELECT *, least(floor(x * {k}), {k} - 1) AS cell FROM p) GROUP BY cell) r ON c.cell = r.cell)"


@query(f"WITH {_SAW} SELECT space, n, {qs('e', 5)} AS err FROM (VALUES ('legendre(1)', 2, {_cells_sql(1)}), ('multiwavelet(2,1)', 8, {_cells_sql(4)}), ('multiwavelet(4,1)', 32, {_cells_sql(16)}), ('multiwavelet(5,1)', 64, {_cells_sql(32)})) v(space, n, e)")
def sawtooth_spaces(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The retail price over all parts, a sawtooth: a line against wavelets of growing resolution, by least squares over the whole table."""
    from .points import saw_points

    p = saw_points(spark, sf_dir)
    out = []
    for spec in (legendre(1), multiwavelet(2, 1), multiwavelet(4, 1), multiwavelet(5, 1)):
        m = baselines.full_expansion_fit(p, unit_axes([2]), [spec])
        out.append((spec.tag, spec.size, error(p, m)))
    return rows(spark, out, "space string, n int, e double").select("space", "n", q("e", 5).alias("err"))


@query()
def single_space_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Compression with one family of spaces only, and with the better of both."""
    points, out = line(spark, sf_dir).persist(), []
    n = points.count()
    axes = grid3(n)
    tensor = grid_tensor(points, axes)
    for name, space in (("polynomials 20", [legendre(20)]), ("polynomials 40", [legendre(40)]), ("wavelets 3, 3", [multiwavelet(3, 3)]), ("wavelets 1, 3", [multiwavelet(1, 3)])):
        m = baselines.single_space(points, axes, space[0], EPS, tensor=tensor, n_points=n)
        out.append((name, m.nnz, m.meta.err_fit, error(points, m), error(points, fitted(points, m))))
    m = compress(points, axes, EPS, tensor=tensor, n_points=n)
    out.append(("better of both", m.nnz, m.meta.err_fit, error(points, m), error(points, fitted(points, m))))
    points.unpersist()
    return rows(spark, out, "space string, nnz int, err_fit double, err_before double, err_after double")


# -- leverage and self-convergence ---------------------------------------------------------------------

_EDGES = [0.0, 0.25, 0.5, 1.0, 2.0, 3.0, 5.0, 1e9]
_CASE = "CASE " + " ".join(f"WHEN x < {e} THEN {i}" for i, e in enumerate(_EDGES[1:])) + " END"
_G = "g AS (SELECT count(*)::DOUBLE AS n, sum(sqrt(3) * (2 * c1 - 1)) AS s, sum(3 * (2 * c1 - 1) * (2 * c1 - 1)) AS ss FROM p)"
_LEVX = "(w0 * w0 * ss - 2 * w0 * w1 * s + w1 * w1 * n) / (n * ss - s * s) * n / 2"
_DCTW = "CASE WHEN out = 0 THEN sqrt(1.0::DOUBLE / len) ELSE sqrt(2.0::DOUBLE / len) * cos(pi() * out * (2 * pos + 1) / (2.0::DOUBLE * len)) END"


@query(
    f"WITH {points_sql()}, {_BLOCKS}, {_G}, o AS (SELECT unnest(range(600)) AS out), m AS (SELECT blk, out, sum(sgn * {_DCTW}) AS w0, sum(sgn * sqrt(3) * (2 * c1 - 1) * {_DCTW}) AS w1 FROM b JOIN o ON out < len GROUP BY blk, out), "
    f"l AS (SELECT 'before' AS stage, {_LEVX} AS x FROM (SELECT 1.0::DOUBLE AS w0, sqrt(3) * (2 * c1 - 1) AS w1 FROM p), g UNION ALL SELECT 'after', {_LEVX} FROM m, g) "
    f"SELECT stage, {_CASE} AS bucket, count(*)::BIGINT AS n_rows FROM l GROUP BY ALL"
)
def leverage_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Histogram of the leverage scores (in units of their mean) of all rows of a line's design before and after signs and block transforms."""
    points, model = line(spark, sf_dir), line_model()
    n = points.count()
    unit = (F.col("lev") * n / 2).alias("lev")
    before = metrics.leverage_histogram(sketch.leverage(points, model).select(unit), _EDGES).select(F.lit("before").alias("stage"), "bucket", F.col("n").alias("n_rows"))
    after = metrics.leverage_histogram(sketch.mixed_leverage(points, model, "dct", 256).select(unit), _EDGES).select(F.lit("after").alias("stage"), "bucket", F.col("n").alias("n_rows"))
    return before.union(after)


@query()
def leverage_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same for the whole model: share of rows in [0.2, 0.5], mean, largest over mean and coefficient of variation, before and after each mixer."""
    points, model = line(spark, sf_dir).persist(), model3(spark, sf_dir)
    out = [("before", *_spread(sketch.leverage(points, model)))]
    for kind in ("dft", "dct", "wht"):
        out.append((kind, *_spread(sketch.mixed_leverage(points, model, kind, 512))))
    points.unpersist()
    return rows(spark, out, "stage string, in_02_05 double, mean double, max_over_mean double, cv double")


def _spread(df: DataFrame) -> tuple:
    s = metrics.leverage_spread(df)
    return s["in_02_05"], s["mean"], s["max_over_mean"], s["cv"]


_PRICE = "c2"
_SIZES = list(range(4, 124, 8))


def _weight(kind: str) -> str:
    if kind == "dct":
        return _DCTW
    if kind == "none":
        return "CASE WHEN out = pos THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END"
    f = "((out + 1) // 2)"
    edge = "(out = 0 OR (len % 2 = 0 AND out = len - 1))"
    return f"CASE WHEN {edge} THEN cos(2 * pi() * {f} * pos / len) WHEN out % 2 = 1 THEN sqrt(2) * cos(2 * pi() * {f} * pos / len) ELSE -sqrt(2) * sin(2 * pi() * {f} * pos / len) END / sqrt(len)"


def _sketch_sql(kinds: tuple[str, ...], share: float) -> str:
    """r: the drawn mixed rows of a line's design, ranked by draw, for each kind."""
    parts = [f"SELECT '{kind}' AS mix, k.blk, k.out, k.h, sum(sgn * {_weight(kind)}) AS w0, sum(sgn * sqrt(3) * (2 * c1 - 1) * {_weight(kind)}) AS w1, sum(sgn * u * {_weight(kind)}) AS u FROM k JOIN b ON k.blk = b.blk GROUP BY k.blk, k.out, k.h" for kind in kinds]
    return f"{points_sql(_PRICE)}, {_BLOCKS}, g0 AS (SELECT DISTINCT blk, len FROM b), d AS (SELECT blk, len, unnest(range(len)) AS out FROM g0), k AS (SELECT blk, out, h FROM (SELECT blk, out, {_DRAW} AS h FROM d) WHERE h < {share}::DOUBLE), s0 AS ({' UNION ALL '.join(parts)}), r AS (SELECT *, row_number() OVER (PARTITION BY mix ORDER BY h, blk, out) AS r FROM s0)"


_CORES = "x AS (SELECT mix, s, sum(w0*w0) AS a, sum(w0*w1) AS b, sum(w1*w1) AS c, sum(w0*u) AS p, sum(w1*u) AS q FROM r, z WHERE r.r <= z.s GROUP BY mix, s), y AS (SELECT mix, s, (p*c - b*q) / (a*c - b*b) AS x0, (a*q - b*p) / (a*c - b*b) AS x1 FROM x)"


@query(
    f"WITH {_sketch_sql(('dct',), 0.05)}, z AS (SELECT unnest({[*_SIZES, _SIZES[-1] + 8]}) AS s), {_CORES}, c AS (SELECT u.s AS s1, v.s AS s2, sqrt(((v.x0-u.x0)*(v.x0-u.x0) + (v.x1-u.x1)*(v.x1-u.x1)) / (u.x0*u.x0 + u.x1*u.x1)) AS c FROM y u JOIN y v ON v.s = u.s + 8), "
    f"m AS (SELECT *, max(c) OVER (ORDER BY s1 ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS most FROM c) SELECT s1, s2, {qs('c', 6)} AS change, s1 IS NOT DISTINCT FROM (SELECT min(s1) FROM m WHERE c < most / 10) AS drop_here FROM m"
)
def self_convergence_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Change of the core from S to S + 8 for a core of two entries, S from 2 R to 58 R, and the S at which it drops."""
    got = refit.self_convergence(line(spark, sf_dir, _PRICE), line_model(), _SIZES, 8, "dct", b=256)
    at = refit.drop_at(got)
    return rows(spark, [(a, b, c, a == at) for a, b, c in got], "s1 int, s2 int, c double, drop_here boolean").select("s1", "s2", q("c", 6).alias("change"), "drop_here")


@query()
def self_convergence_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same for the model: step a fifth of R, S from 0.6 R to 8 R; ``drop_over_r`` is the S of the drop over R (null without one)."""
    points, model = line(spark, sf_dir), model3(spark, sf_dir)
    r, step = model.R, max(1, round(0.2 * model.R))
    got = refit.self_convergence(points, model, list(range(round(0.6 * r), 8 * r, step)), step, b=256)
    at = refit.drop_at(got)
    return rows(spark, [(s, s / r, c, None if at is None else at / r) for s, _, c in got], "s int, s_over_r double, change double, drop_over_r double")


_OVER = (2, 3, 4, 5, 8, 16)


@query(
    f"WITH {_sketch_sql(('dct', 'dft', 'none'), 0.02)}, z AS (SELECT unnest({list(_OVER)}) AS s), {_CORES}, f AS (SELECT regr_slope(u, c1) / 2 / sqrt(3) AS f1, regr_intercept(u, c1) + regr_slope(u, c1) / 2 AS f0 FROM p) "
    f"SELECT mix, s, s / 2.0::DOUBLE AS s_over_r, {qs('sqrt(((x0-f0)*(x0-f0) + (x1-f1)*(x1-f1)) / (f0*f0 + f1*f1))', 4)} AS away FROM y, f"
)
def oversampling_2param(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distance of the sketched core from the one of all points, by mixer and oversampling, for a core of two entries."""
    points, model = line(spark, sf_dir, _PRICE), line_model()
    n = points.count()
    full = refit.refit_full(points, model).core.ravel()
    out = []
    for mix in ("dct", "dft", "none"):
        for s, got in zip(_OVER, refit.refit_sizes(points, model, list(_OVER), mix, b=256, total=n)):
            out.append((mix, s, s / 2, float(np.linalg.norm(got.model.core.ravel() - full) / np.linalg.norm(full))))
    return rows(spark, out, "mix string, s int, s_over_r double, e double").select("mix", "s", "s_over_r", q("e", 4).alias("away"))


@query()
def oversampling_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Error at all points of the model's sketched core over that of the full solution, by mixer and S / R."""
    points = line(spark, sf_dir).persist()
    model = model3(spark, sf_dir, None, ranks=[4, 4, 2])
    total, best, got = points.count(), fitted(points, model), []
    over = (0.8, 1.0, 1.5, 2.0, 2.5, 4.0, 8.0)
    for mix in ("none", "dft", "dct", "wht", "gauss", "sparse_sign"):
        got += [(mix, k, r) for k, r in zip(over, refit.refit_sizes(points, model, [max(1, round(k * model.R)) for k in over], mix, b=256, total=total))]
    least, *errors = metrics.core_errors(points, model, [best.core, *[r.model.core for *_, r in got]])
    out = [(mix, k, r.s, r.underdetermined, e / least) for (mix, k, r), e in zip(got, errors)]
    points.unpersist()
    return rows(spark, out, "mix string, s_over_r double, s int, underdetermined boolean, error_over_full double")


# -- interpolation -------------------------------------------------------------------------------------

_RATES = (0.05, 0.1, 0.5, 1.0)
_O = "o AS (SELECT o_orderkey AS k, greatest(0.0::DOUBLE, least(1.0::DOUBLE, date_diff('day', DATE '1995-01-01', o_orderdate::DATE) / 2500.0::DOUBLE)) AS c1, o_totalprice / 500000.0::DOUBLE + date_diff('day', DATE '1995-01-01', o_orderdate::DATE) / 2500.0::DOUBLE AS u FROM orders)"


@query(
    f"WITH {_O}, h AS (SELECT c1, u, ('0x' || substr(md5(k || '/0'), 1, 8))::BIGINT / 4294967296.0::DOUBLE AS h FROM o), s AS (SELECT rate, c1, u FROM h, (SELECT unnest({list(_RATES)}::DOUBLE[]) AS rate) WHERE rate >= 1 OR h < rate), "
    "w AS (SELECT 'nearest' AS kind, rate, floor(c1 * 8 + 0.5) AS i, 1.0::DOUBLE AS w, u FROM s UNION ALL SELECT 'tent', rate, least(floor(c1 * 8), 7) + e, CASE WHEN e = 1 THEN c1 * 8 - least(floor(c1 * 8), 7) ELSE 1 - (c1 * 8 - least(floor(c1 * 8), 7)) END, u FROM s, (SELECT unnest([0, 1]) AS e)), "
    "v AS (SELECT kind, rate, i / 8 AS y, sum(w * u) / sum(w) AS v FROM w GROUP BY kind, rate, i HAVING sum(w) > 0), f AS (SELECT kind, rate, regr_slope(v, y) AS b, regr_intercept(v, y) AS a FROM v GROUP BY kind, rate), "
    "x AS (SELECT regr_slope(u, c1) AS b, regr_intercept(u, c1) AS a FROM o) "
    f"SELECT kind, rate, {qs('sqrt(sum((u - f.a - f.b * c1) * (u - f.a - f.b * c1)) / sum(u * u))', 6)} AS err_before, {qs('sqrt(sum((u - x.a - x.b * c1) * (u - x.a - x.b * c1)) / sum(u * u))', 6)} AS err_after FROM f, o, x GROUP BY kind, rate"
)
def regrid_study_2param(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Kind of interpolation and share of the points: a line through the nodes' values against the line of all points, at all points (price and day of the orders)."""
    day = "greatest(0.0D, least(1.0D, datediff(o_orderdate, DATE'1995-01-01') / 2500.0D))"
    p = tables.table(spark, sf_dir, "orders").select(F.col("o_orderkey").cast("string").alias("pt_key"), F.expr(day).alias("c1"), (F.col("o_totalprice") / 500000.0 + F.expr("datediff(o_orderdate, DATE'1995-01-01') / 2500.0D")).alias("u"))
    axes, out = unit_axes([9]), []
    line1 = FunctionalTucker(axes, np.zeros(2), [line_model().functions[0]])
    after = error(p, refit.refit_full(p, line1))
    for kind, f in (("nearest", regrid.nearest), ("tent", regrid.tent_average)):
        for rate in _RATES:
            t = f(sampling.hash_fraction(p, rate, 0), axes).where("support > 0").toPandas()  # nine nodes at most
            b, a = np.polyfit(t["i1"].to_numpy() / 8, t["v"].to_numpy(), 1)
            out.append((kind, rate, error(p, line1.with_core(np.array([a + b / 2, b / 2 / np.sqrt(3)]))), after))
    return rows(spark, out, "kind string, rate double, x double, y double").select("kind", "rate", q("x").alias("err_before"), q("y").alias("err_after"))


@query()
def regrid_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Kind x share for the model, with and without the sketched re-estimation from all points."""
    points, out = line(spark, sf_dir).persist(), []
    n, s = points.count(), 4 * 4 * 4 * 2
    part = cut(sketch.drawn_points(points, 3, s, b=256, total=n), "drawn")  # of every sketch below
    for kind in ("local_linear", "tent_average", "nearest"):
        for rate in _RATES:
            axes = grid3(n, rate)
            m = compress(points, axes, None, rate, kind, ranks=[4, 4, 2], n_points=n)
            cores = [m.core, refit.refit_core(part, m, s, b=256, total=n).model.core, fitted(points, m).core]
            out.append((kind, rate, "x".join(str(a.nodes) for a in axes), *metrics.core_errors(points, m, cores)))
    points.unpersist()
    discard(part)
    return rows(spark, out, "regridder string, rate double, grid string, err_before double, err_sketch double, err_full double")


@query("SELECT unnest(['local_linear', 'nearest', 'tent_average']) AS regridder, true AS refit_helps")
def regrid_fidelity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The re-estimated core never has a larger error at the points than the one that interpolation gave, whatever the kind."""
    points, out = line(spark, sf_dir).persist(), []
    n = points.count()
    for kind in ("local_linear", "tent_average", "nearest"):
        m = compress(points, grid3(n), None, regridder=kind, ranks=[4, 4, 2], n_points=n)
        out.append((kind, bool(error(points, fitted(points, m)) <= error(points, m) * (1 + 1e-9))))
    points.unpersist()
    return rows(spark, out, "regridder string, refit_helps boolean")


# -- eleven variables ----------------------------------------------------------------------------------

#: Variables whose jobs run beside each other: most are short and wait for the driver.
BESIDE = 4


def together(spark: SparkSession, f: Callable[[str], tuple], names: Iterable[str]) -> list[tuple]:
    """f of every name, some at a time, in order."""
    f = inheritable_thread_target(spark)(f)
    with ThreadPoolExecutor(BESIDE) as pool:
        return list(pool.map(f, names))


_ELEVEN = {6000: "('constant', 0.0::DOUBLE, true), ('affine', 0.0, true), ('product', 0.0, true), ('quadratic', 0.0, true), ('front', 0.3, false), ('sharp_front', 0.4, false), ('wave', 1.0, false), ('short_wave', 1.0, false), ('step', 0.3, false), ('separable_sum', 0.0, true), ('noise', 0.5, false)", 60000: "('constant', 0.0::DOUBLE, true), ('affine', 0.0, true), ('product', 0.0, true), ('quadratic', 0.0, true), ('front', 0.0, false), ('sharp_front', 0.2, false), ('wave', 0.7, false), ('short_wave', 1.0, false), ('step', 0.0, true), ('separable_sum', 0.0, true), ('noise', 0.5, false)"}


@query(measured(_ELEVEN, "lineitem", "name, err, reached"))
def eleven_variables(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = eleven_report(spark, sf_dir)
    return r.select(F.col("n_points").cast("int").alias("n_points"), "name", q("err_points", 1).alias("err"), "reached")


@query()
def eleven_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ranks, achieved error (after the core's re-estimation from all points) and ratio of all eleven variables, a tenth of the points regridded on shared axes. ``reached``: the error is within twice the requested one; without it the ratio is no compression at that precision."""
    wide = tables.line_points_multi(spark, sf_dir).withColumn("noise", sampling.hash01(F.col("pt_key"), "noise"))
    n = wide.count()
    axes = grid3(n, RATE)
    part = cut(sampling.hash_fraction(wide, RATE).drop("pt_key"), "part")  # of every variable: keys are hashed once
    noise = cut(wide.select("c1", "c2", "c3", "noise"), "noise")

    def one(name: str) -> tuple:
        of = lambda df: df.select("c1", "c2", "c3", F.col(name).alias("u"))
        p = of(noise if name == "noise" else wide)
        m = fitted(p, compress(p, axes, EPS, RATE, tensor=grid_tensor(of(part), axes), n_points=n))
        err = metrics.shared_error(p, m)
        return n, name, "x".join(map(str, m.ranks)), err, metrics.storage(m, n)["ratio_values"], bool(err <= 2 * EPS)

    out = together(spark, one, reversed(tables.ELEVEN))[::-1]  # the last ones have the largest cores
    discard(part)
    discard(noise)
    return rows(spark, out, "n_points long, name string, ranks string, err_points double, ratio double, reached boolean")


# -- slices and cost -----------------------------------------------------------------------------------

_SLICE = "g AS (SELECT a.i / 11.0::DOUBLE AS c1, b.i / 11.0::DOUBLE AS c2, 0.4::DOUBLE AS c3, 0.7::DOUBLE AS c4 FROM unnest(range(12)) a(i), unnest(range(12)) b(i))"


@query(f"WITH {_SLICE} SELECT {qs('c1', 4)} AS c1, {qs('c2', 4)} AS c2, {qs(tables.FRONT3, 5)} AS u3, {qs(tables.FRONT4, 5)} AS u4, true AS close3, true AS close4 FROM g")
def slice_agreement(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Decoded slices of both cases against the planted truth, node by node (``slice_report``: their errors)."""
    a, b = _slices(spark, sf_dir)
    near = lambda e: (F.abs(F.col("u_hat") - F.col("u")) < e)
    a = a.select(q("c1", 4).alias("c1"), q("c2", 4).alias("c2"), q("u", 5).alias("u3"), near(0.3).alias("close3"))
    b = b.select(q("c1", 4).alias("c1"), q("c2", 4).alias("c2"), q("u", 5).alias("u4"), near(0.8).alias("close4"))
    return a.join(b, ["c1", "c2"])


def _slices(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    three = fitted(line(spark, sf_dir), model3(spark, sf_dir))
    points4 = tables.order_points(spark, sf_dir)
    four = fitted(points4, model4(spark, sf_dir))
    a = decode.slice_at(spark, three, {"c3": 0.4}, [12, 12, 1]).withColumn("u", F.expr(tables.FRONT3))
    b = decode.slice_at(spark, four, {"c3": 0.4, "c4": 0.7}, [12, 12, 1, 1]).withColumn("u", F.expr(tables.FRONT4))
    return a, b


@query()
def slice_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = []
    for name, s in zip(("three axes", "four axes"), _slices(spark, sf_dir)):
        out.append((name, metrics.rel_fro(s), s.agg(F.max(F.abs(F.col("u") - F.col("u_hat")))).first()[0]))
    return rows(spark, out, "name string, relative_error double, max_abs_error double")


@query("SELECT count(*)::BIGINT AS n_decoded, true AS fewer_than_spaces FROM lineitem")
def decode_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All points decoded; basis functions a point against the sizes of the spaces (``decode_report``: times)."""
    points, model = line(spark, sf_dir), model3(spark, sf_dir)
    full = sum(max(f.basis.size for f in fs) * len({f.basis for f in fs}) for fs in model.functions)
    return rows(spark, [(decode.all_points(points, model).where("u_hat IS NOT NULL").count(), decode.basis_evaluations(model) <= full)], "n_decoded long, fewer_than_spaces boolean")


@query()
def decode_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds to compress and to decode all points, and basis functions evaluated a point."""
    points = line(spark, sf_dir).persist()
    n = points.count()
    t0 = time.time()
    model = model3(spark, sf_dir)
    t1 = time.time()
    decode.all_points(points, model).write.format("noop").mode("overwrite").save()
    t2 = time.time()
    points.unpersist()
    return rows(spark, [(n, t1 - t0, t2 - t1, decode.basis_evaluations(model))], "n long, compress_seconds double, decode_seconds double, basis_evaluations int")


@query("SELECT true AS values_beat_dense")
def dense_tucker_comparison(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Functional storage against core and factor columns on a fine grid of a smooth field."""
    dims = [128, 128, 64]
    t = planted(spark, tables.FRONT3, dims)
    model = compress(line(spark, sf_dir), unit_axes(dims), 1e-2, candidates=[legendre(30), multiwavelet(3, 3)], tensor=t)
    return rows(spark, [(metrics.storage(model)["values_only"] < metrics.dense_tucker_bytes(model.ranks, dims),)], "values_beat_dense boolean")


@query("SELECT true AS model_smaller")
def codec_baseline(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parquet files of the same value column against the model bundle."""
    from ..operators.storage import folder, remove

    path = folder(spark, "codec")
    line(spark, sf_dir).select("u").write.parquet(path)
    size = metrics.on_disk(spark, path)
    remove(spark, path)
    return rows(spark, [(metrics.storage(model3(spark, sf_dir))["with_indices"] < size,)], "model_smaller boolean")


_GLOBAL = f"w AS (SELECT row_number() OVER (ORDER BY {hint('pt_key', 'mix0', 1)}, pt_key, c1, c2, c3, u) - 1 AS q, (1 - 2 * ({hint('pt_key', 'mix0', 2)} % 2)) AS sgn, c1, u FROM p), n AS (SELECT count(*) AS n, ceil(count(*) / ceil(count(*) / 1024.0))::BIGINT * ceil(count(*) / 1024.0)::BIGINT AS len FROM p), o AS (SELECT out, row_number() OVER (ORDER BY ('0x' || substr(md5('0-' || out || '/0'), 1, 8))::BIGINT, out) AS r FROM (SELECT unnest(range((SELECT len FROM n))) AS out))"


@query(f"WITH {points_sql(_PRICE)}, {_GLOBAL}, t AS (SELECT out, len, q AS pos, sgn, c1, u FROM w, n, (SELECT out FROM o WHERE r <= 12)) SELECT out::BIGINT AS out, {qs('sum(sgn * (' + _weight('dft') + '))', 5)} AS w0, {qs('sum(sgn * sqrt(3) * (2 * c1 - 1) * (' + _weight('dft') + '))', 5)} AS w1, {qs('sum(sgn * u * (' + _weight('dft') + '))', 5)} AS u FROM t GROUP BY out")
def global_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Twelve rows of one Fourier transform over all points (the literal form of the sketch), in two steps."""
    points = line(spark, sf_dir, _PRICE)
    n = points.count()
    a, b = sketch.global_rows(points, line_model(), 12, 0, n)
    q2 = -(-n // 1024)
    outs = sketch.global_outputs(points, -(-n // q2) * q2, 12, 0)
    return rows(spark, [(int(o), float(x[0]), float(x[1]), float(y)) for o, x, y in zip(outs, a, b)], "out long, w0 double, w1 double, u double").select("out", *[q(c, 5).alias(c) for c in ("w0", "w1", "u")])


@query("SELECT unnest(['block', 'global', 'partition']) AS scope, true AS exact")
def mixing_scopes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A field in the span is recovered by every scope of the transform."""
    from .refits import SPAN, literal_model

    points, out = line(spark, sf_dir, SPAN), []
    for scope in ("block", "global", "partition"):
        got = refit.refit_core(points, literal_model(), 30, scope=scope, b=256).model.core.ravel()
        out.append((scope, bool(np.abs(got - np.array([1.0, 0.5, -2.0, 0.25])).max() < 1e-6)))
    return rows(spark, out, "scope string, exact boolean")


@query(f"WITH {points_sql(tables.AFFINE)}, g AS (SELECT a.i / 4.0::DOUBLE AS c1, b.i / 4.0::DOUBLE AS c2 FROM unnest(range(5)) a(i), unnest(range(5)) b(i)) SELECT {qs('c1', 4)} AS c1, {qs('c2', 4)} AS c2, {qs('1 + 2 * c1 - c2', 5)} AS u FROM g WHERE c1 BETWEEN 0.2 AND 0.8 AND c2 BETWEEN 0.2 AND 0.8")
def regrid_triangulated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Triangulation as a reference for the regridders: all points are averaged by cells of 16 x 16 first (means of an affine field lie on it), then the means are triangulated; exact at the nodes."""
    cells = line(spark, sf_dir).select(F.least(F.floor(F.col("c1") * 16), F.lit(15)).alias("i"), F.least(F.floor(F.col("c2") * 16), F.lit(15)).alias("j"), "c1", "c2", (1 + 2 * F.col("c1") - F.col("c2")).alias("u"))
    p = cells.groupBy("i", "j").agg(F.avg("c1").alias("c1"), F.avg("c2").alias("c2"), F.avg("u").alias("u")).orderBy("i", "j").toPandas()  # 256 cells at most
    g = np.array([(a / 4, b / 4) for a in range(5) for b in range(5) if 0.2 <= a / 4 <= 0.8 and 0.2 <= b / 4 <= 0.8])
    v = regrid.barycentric_2d(p[["c1", "c2"]].to_numpy(), p["u"].to_numpy(), g)
    return rows(spark, [(float(x), float(y), float(u)) for (x, y), u in zip(g, v)], "c1 double, c2 double, u double").select(q("c1", 4).alias("c1"), q("c2", 4).alias("c2"), q("u", 5).alias("u"))


@query(f"WITH o AS (SELECT l_linestatus AS s, l_returnflag AS f, sum(l_quantity) AS v FROM lineitem GROUP BY ALL) SELECT dense_rank() OVER (ORDER BY s)::INTEGER - 1 AS i1, dense_rank() OVER (ORDER BY f)::INTEGER - 1 AS i2, {qs('v', 3)} AS v, 1.0::DOUBLE AS support FROM o")
def structured_tensor(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Data that already sit on nodes go through unchanged."""
    from ..operators.axes import index_axis

    t = tables.table(spark, sf_dir, "lineitem")
    cells = t.groupBy("l_linestatus", "l_returnflag").agg(F.sum("l_quantity").alias("v"))
    for i, c in (("i1", "l_linestatus"), ("i2", "l_returnflag")):
        cells = cells.join(F.broadcast(index_axis(t, c).withColumnsRenamed({"value": c, "id": i})), c)
    return regrid.identity(cells, unit_axes([2, 3])).withColumn("v", q("v", 3))


@query(f"WITH x AS (SELECT DISTINCT l_quantity AS x FROM lineitem) SELECT (row_number() OVER (ORDER BY x) - 1)::INTEGER AS i, {qs('x / sqrt((SELECT sum(x * x) FROM x))', 7)} AS v1 FROM x")
def factor_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The only singular vector of the charge's first axis: the levels of the quantity at length one."""
    found = tucker.st_hosvd(charge_tensor(spark, sf_dir), CHARGE_DIMS, eps=1e-6)
    samples = funcfit.vector_samples(spark, found.factors, unit_axes(CHARGE_DIMS))
    return metrics.factor_table(samples).select("i", q("1", 7).alias("v1"))
