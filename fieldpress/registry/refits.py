"""Queries on design rows, least squares, leverage, mixing and sketches."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import decode, lstsq, metrics, mixing, sketch
from ..operators.axes import unit_axes
from ..plans import refit
from ..plans.model import FunctionalTucker, ModeFunction
from ..schema import legendre
from ..sources import tables
from .base import hint, line, model3, points_sql, q, qs, query, rows


def literal_model(core: np.ndarray | None = None) -> FunctionalTucker:
    """Two functions (1 and the linear Legendre polynomial) on each of the first two axes, one constant on the third."""
    one, lin = ModeFunction(legendre(1), {0: 1.0}), ModeFunction(legendre(1), {1: 1.0})
    core = np.array([[[1.0], [0.5]], [[-2.0], [0.25]]]) if core is None else core
    return FunctionalTucker(unit_axes([11, 11, 11]), core, [[one, lin], [one, lin], [one]])


def line_model() -> FunctionalTucker:
    """A straight line in c1: two unknowns."""
    one, lin = ModeFunction(legendre(1), {0: 1.0}), ModeFunction(legendre(1), {1: 1.0})
    return FunctionalTucker(unit_axes([11, 11, 11]), np.zeros((2, 1, 1)), [[one, lin], [one], [one]])


_L1, _L2 = "(sqrt(3) * (2 * c1 - 1))", "(sqrt(3) * (2 * c2 - 1))"
_PRICE = "c2"


@query(f"WITH {points_sql()} SELECT pt_key, {qs('1')} AS w1, {qs(_L2)} AS w2, {qs(_L1)} AS w3, {qs(f'{_L1} * {_L2}')} AS w4 FROM p")
def design_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..operators import design

    w = design.rows(line(spark, sf_dir), literal_model())
    return w.select("pt_key", *[q(F.col("w")[i]).alias(f"w{i + 1}") for i in range(4)])


@query(f"WITH {points_sql(_PRICE)}, r AS (SELECT regr_slope(u, c1) AS b, regr_intercept(u, c1) AS a FROM p) SELECT {qs('a + b / 2', 7)} AS a0, {qs('b / 2 / sqrt(3)', 7)} AS a1 FROM r")
def full_ls_2param(spark: SparkSession, sf_dir: str) -> DataFrame:
    core = lstsq.full(line(spark, sf_dir, _PRICE), line_model()).core
    return rows(spark, [(float(core[0]), float(core[1]))], "a double, b double").select(q("a", 7).alias("a0"), q("b", 7).alias("a1"))


@query(f"WITH {points_sql(_PRICE)}, r AS (SELECT regr_slope(u, c1) AS b, regr_intercept(u, c1) AS a FROM p) SELECT {qs('a + b / 2', 7)} AS a0, {qs('b / 2 / sqrt(3)', 7)} AS a1 FROM r")
def full_ls_tsqr(spark: SparkSession, sf_dir: str) -> DataFrame:
    core = lstsq.full(line(spark, sf_dir, _PRICE), line_model(), "tsqr").core
    return rows(spark, [(float(core[0]), float(core[1]))], "a double, b double").select(q("a", 7).alias("a0"), q("b", 7).alias("a1"))


@query(f"WITH {points_sql(_PRICE)}, r AS (SELECT regr_slope(u, c1) AS b, regr_intercept(u, c1) AS a FROM p) SELECT {qs('a + b / 2', 6)} AS a0, {qs('b / 2 / sqrt(3)', 6)} AS a1 FROM r")
def full_ls_iterative(spark: SparkSession, sf_dir: str) -> DataFrame:
    core = lstsq.lsqr(line(spark, sf_dir, _PRICE), line_model(), tol=1e-14).core
    return rows(spark, [(float(core[0]), float(core[1]))], "a double, b double").select(q("a", 6).alias("a0"), q("b", 6).alias("a1"))


#: A field in the span of the literal model, so that its core can be recovered exactly.
SPAN = f"1e0 + 0.5e0*{_L2} - 2e0*{_L1} + 0.25e0*{_L1}*{_L2}"
_CORE = "SELECT unnest([1, 2, 3, 4]) AS j, unnest([1.0::DOUBLE, 0.5, -2.0, 0.25]) AS v"


def _core(spark: SparkSession, core: np.ndarray) -> DataFrame:
    return rows(spark, [(i + 1, float(v)) for i, v in enumerate(core.ravel())], "j int, v double").select("j", q("v", 6).alias("v"))


@query(_CORE)
def full_ls_planted_core(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _core(spark, lstsq.full(line(spark, sf_dir, SPAN), literal_model()).core)


@query(_CORE)
def sketched_ls_exact_field(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _core(spark, refit.refit_core(line(spark, sf_dir, SPAN), literal_model(), 10, b=256).model.core)


@query("SELECT unnest(['dct', 'dft', 'gauss', 'none', 'partition', 'sparse_sign', 'wht']) AS mix, true AS exact")
def sketched_ls_all_mixers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every mixer and projection recovers a core whose field is in the span."""
    points, truth = line(spark, sf_dir, SPAN), np.array([1.0, 0.5, -2.0, 0.25])
    out = []
    for mix in ("dft", "dct", "wht", "none", "gauss", "sparse_sign"):
        out.append((mix, bool(np.abs(refit.refit_core(points, literal_model(), 40, mix=mix, b=256).model.core.ravel() - truth).max() < 1e-6)))
    out.append(("partition", bool(np.abs(refit.refit_core(points, literal_model(), 40, scope="partition", b=256).model.core.ravel() - truth).max() < 1e-6)))
    return rows(spark, out, "mix string, exact boolean")


@query(_CORE)
def leverage_sampled_ls(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _core(spark, sketch.leverage_ls(line(spark, sf_dir, SPAN), literal_model(), 60))


@query(_CORE)
def refit_top_entries(spark: SparkSession, sf_dir: str) -> DataFrame:
    start = np.array([[[0.9], [0.5]], [[-1.7], [0.25]]])
    return _core(spark, refit.refit_top(line(spark, sf_dir, SPAN), literal_model(start), 2).core)


# -- leverage ------------------------------------------------------------------------------------------

_LEV = "l AS (SELECT pt_key, 1.0::DOUBLE / (SELECT count(*) FROM p) + (c1 - (SELECT avg(c1) FROM p)) * (c1 - (SELECT avg(c1) FROM p)) / (SELECT sum(c1 * c1) - sum(c1) * sum(c1) / count(*) FROM p) AS lev FROM p)"


@query(f"WITH {points_sql()}, {_LEV} SELECT pt_key, {qs('lev', 9)} AS lev FROM l")
def leverage_line(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sketch.leverage(line(spark, sf_dir), line_model()).select("pt_key", q("lev", 9).alias("lev"))


@query("SELECT 4.0::DOUBLE AS total, true AS within_unit")
def leverage_sum(spark: SparkSession, sf_dir: str) -> DataFrame:
    lev = sketch.leverage(line(spark, sf_dir), literal_model())
    return lev.agg(q(F.sum("lev"), 6).alias("total"), (F.min("lev") >= 0).alias("lo"), (F.max("lev") <= 1).alias("hi")).select("total", (F.col("lo") & F.col("hi")).alias("within_unit"))


@query(f"WITH {points_sql()}, {_LEV}, s AS (SELECT lev * (SELECT count(*) FROM p) AS x FROM l), b AS (SELECT CASE WHEN x < 1.5 THEN 0 WHEN x < 2.5 THEN 1 ELSE 2 END AS bucket FROM s WHERE x >= 0 AND x <= 10) SELECT bucket, [0.0::DOUBLE, 1.5, 2.5][bucket + 1] AS lo, [1.5::DOUBLE, 2.5, 10.0][bucket + 1] AS hi, count(*)::BIGINT AS n FROM b GROUP BY bucket")
def leverage_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = line(spark, sf_dir)
    n = points.count()
    lev = sketch.leverage(points, line_model()).select((F.col("lev") * n).alias("lev"))
    return metrics.leverage_histogram(lev, [0.0, 1.5, 2.5, 10.0])


@query("SELECT true AS total_kept, true AS spread_bounded")
def leverage_after_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mixing keeps the sum of the scores; their spread stays that of squared sums of random signs (see ``leverage_mixing`` for skewed rows)."""
    points, model = line(spark, sf_dir), literal_model()
    before = sketch.leverage(points, model).agg(F.sum("lev")).first()[0]
    out = []
    for kind in ("dft", "wht", "dct"):
        after = sketch.mixed_leverage(points, model, kind, 256)
        total = after.agg(F.sum("lev")).first()[0]
        out.append((abs(total - before) < 1e-6, metrics.leverage_spread(after)["cv"] < 2.5))
    return rows(spark, [(all(x[0] for x in out), all(x[1] for x in out))], "total_kept boolean, spread_bounded boolean")


@query("SELECT true AS exact_on_grid")
def product_leverage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """On a whole product grid the product over axes is the leverage."""
    model = literal_model()
    g = decode.slice_at(spark, model, {"c3": 0.5}).select(F.concat_ws("-", "c1", "c2").alias("pt_key"), "c1", "c2", "c3", F.col("u_hat").alias("u"))
    both = sketch.product_leverage(sketch.leverage(g, model), model)
    # the third axis has one point of the grid's eleven here: its constant has leverage 1/11
    return both.agg((F.max(F.abs(F.col("lev") - 11 * F.col("lev_proxy"))) < 1e-9).alias("exact_on_grid"))


# -- signs, blocks, transforms -------------------------------------------------------------------------


@query(f"WITH {points_sql()} SELECT pt_key, (1 - 2 * ({hint('pt_key', 'mix0', 2)} % 2))::INTEGER AS sgn FROM p")
def row_signs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.signs(line(spark, sf_dir)).select("pt_key", "sgn")


_BLOCKS = f"n AS (SELECT greatest(1, round(count(*) / 256.0))::BIGINT AS nb FROM p), b AS (SELECT pt_key, c1, u, {hint('pt_key', 'mix0', 0)} % nb AS blk, row_number() OVER (PARTITION BY {hint('pt_key', 'mix0', 0)} % nb ORDER BY {hint('pt_key', 'mix0', 1)}, pt_key, c1, c2, c3, u) - 1 AS pos, count(*) OVER (PARTITION BY {hint('pt_key', 'mix0', 0)} % nb) AS len, (1 - 2 * ({hint('pt_key', 'mix0', 2)} % 2)) AS sgn FROM p, n)"


@query(f"WITH {points_sql()}, {_BLOCKS} SELECT pt_key, blk, pos::INTEGER AS pos FROM b")
def row_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.positions(mixing.blocks(line(spark, sf_dir), 256)).select("pt_key", "blk", "pos")


def event_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All events in blocks of 32 by number (the last one is shorter)."""
    e = tables.table(spark, sf_dir, "events").select("event_id", "value")
    return e.select(F.floor(F.col("event_id") / 32).cast("long").alias("blk"), F.pmod("event_id", F.lit(32)).cast("int").alias("pos"), F.col("value").alias("x"))


_EV = "w AS (SELECT event_id // 32 AS blk, (event_id % 32)::INTEGER AS pos, value AS x, count(*) OVER (PARTITION BY event_id // 32) AS len FROM events), o AS (SELECT unnest(range(32))::INTEGER AS out)"
_DFT = "CASE WHEN out = 0 OR (len % 2 = 0 AND out = len - 1) THEN cos(2 * pi() * ((out + 1) // 2) * pos / len) / sqrt(len) WHEN out % 2 = 1 THEN sqrt(2) * cos(2 * pi() * ((out + 1) // 2) * pos / len) / sqrt(len) ELSE -sqrt(2) * sin(2 * pi() * (out // 2) * pos / len) / sqrt(len) END"
_DCT = "CASE WHEN out = 0 THEN sqrt(1.0::DOUBLE / len) ELSE sqrt(2.0::DOUBLE / len) * cos(pi() * out * (2 * pos + 1) / (2.0::DOUBLE * len)) END"
_WHT = "(1 - 2 * (bit_count(out & pos) % 2)) / sqrt(len)"


def _mixed_sql(weight: str) -> str:
    return f"WITH {_EV} SELECT blk, out, {qs(f'sum(x * {weight})', 5)} AS y FROM w, o WHERE out < len GROUP BY blk, out"


@query(_mixed_sql(_DFT))
def block_dft(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_values(event_blocks(spark, sf_dir), "dft").select("blk", "out", q("y", 5).alias("y"))


@query(_mixed_sql(_DCT))
def block_dct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_values(event_blocks(spark, sf_dir), "dct").select("blk", "out", q("y", 5).alias("y"))


@query(_mixed_sql(_WHT))
def block_wht(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_values(event_blocks(spark, sf_dir), "wht").select("blk", "out", q("y", 5).alias("y"))


@query(f"WITH {_EV} SELECT kind, {qs('sum(x * x)', 3)} AS energy FROM w, (VALUES ('dft'), ('dct'), ('wht')) k(kind) GROUP BY kind")
def mix_energy_preserved(spark: SparkSession, sf_dir: str) -> DataFrame:
    src, out = event_blocks(spark, sf_dir), None
    for kind in ("dft", "dct", "wht"):
        e = mixing.mix_values(src, kind).agg(F.sum(F.col("y") * F.col("y")).alias("e")).select(F.lit(kind).alias("kind"), q("e", 3).alias("energy"))
        out = e if out is None else out.union(e)
    return out


@query(f"WITH x AS (SELECT event_id AS q, value AS x FROM events), n AS (SELECT (ceil(count(*) / 30.0) * 30)::BIGINT AS n FROM x), f AS (SELECT unnest([0, 1, 5, 100, 479]) AS f) SELECT f::BIGINT AS f, {qs('sum(x * cos(2 * pi() * f * q / n)) / sqrt(max(n))', 5)} AS re, {qs('-sum(x * sin(2 * pi() * f * q / n)) / sqrt(max(n))', 5)} AS im FROM x, f, n GROUP BY f")
def factored_global_dft(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One transform over all events in 30 residue classes; the length is rounded up to whole classes."""
    e = tables.table(spark, sf_dir, "events").select(F.col("event_id").alias("q"), F.col("value").alias("x"))
    return mixing.factored_dft(e, -(-e.count() // 30), 30, [0, 1, 5, 100, 479]).select("f", q("re", 5).alias("re"), q("im", 5).alias("im"))


@query("SELECT way, j, v FROM (SELECT unnest(['full', 'sketch']) AS way), (SELECT unnest([1, 2, 3, 4]) AS j, unnest([1.0::DOUBLE, 0.5, -2.0, 0.25]) AS v)")
def large_core_ways(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ways for cores beyond the driver (limits set to nothing): all points by conjugate gradients, and a stored sketch."""
    points = line(spark, sf_dir, SPAN)
    full = lstsq.full(points, literal_model(), max_r=0)
    part = refit.refit_core(points, literal_model(), 40, b=256, max_bytes=0)
    return _core(spark, full.core).select(F.lit("full").alias("way"), "*").union(_core(spark, part.model.core).select(F.lit("sketch").alias("way"), "*"))


_DRAW = "('0x' || substr(md5(blk || '-' || out || '/0'), 1, 8))::BIGINT / 4294967296.0::DOUBLE"


@query(f"WITH {points_sql()}, {_BLOCKS}, g AS (SELECT DISTINCT blk, len FROM b), d AS (SELECT blk, unnest(range(len)) AS out FROM g) SELECT blk, out::INTEGER AS out, {qs('h', 9)} AS h FROM (SELECT blk, out, {_DRAW} AS h FROM d) WHERE h < 0.02::DOUBLE")
def uniform_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sketch.mixed_rows(line(spark, sf_dir), line_model(), 0.02, b=256).select("blk", "out", q("h", 9).alias("h"))


_DCTB = "CASE WHEN out = 0 THEN sqrt(1.0::DOUBLE / len) ELSE sqrt(2.0::DOUBLE / len) * cos(pi() * out * (2 * pos + 1) / (2.0::DOUBLE * len)) END"
_SKETCH = f"WITH {points_sql(_PRICE)}, {_BLOCKS}, g AS (SELECT DISTINCT blk, len FROM b), d AS (SELECT blk, unnest(range(len)) AS out FROM g), k AS (SELECT blk, out, {_DRAW} AS h FROM d), s AS (SELECT k.blk, k.out, k.h, sum(sgn * {_DCTB}) AS w0, sum(sgn * sqrt(3) * (2 * c1 - 1) * {_DCTB}) AS w1, sum(sgn * u * {_DCTB}) AS u FROM k JOIN b ON k.blk = b.blk WHERE k.h < 0.02::DOUBLE GROUP BY k.blk, k.out, k.h), r AS (SELECT *, row_number() OVER (ORDER BY h, blk, out) AS r FROM s)"
_SOLVE = "SELECT sum(w0*w0) AS a, sum(w0*w1) AS b, sum(w1*w1) AS c, sum(w0*u) AS p, sum(w1*u) AS q FROM r WHERE r <= {n}"


@query(f"{_SKETCH} SELECT {qs('(p*c - b*q) / (a*c - b*b)', 6)} AS a0, {qs('(a*q - b*p) / (a*c - b*b)', 6)} AS a1 FROM ({_SOLVE.format(n=100)})")
def sketched_ls_2param(spark: SparkSession, sf_dir: str) -> DataFrame:
    core = refit.refit_core(line(spark, sf_dir, _PRICE), line_model(), 100, mix="dct", b=256).model.core.ravel()
    return rows(spark, [(float(core[0]), float(core[1]))], "a double, b double").select(q("a", 6).alias("a0"), q("b", 6).alias("a1"))


_TWO = "x AS ({x}), y AS ({y}), v AS (SELECT (x.p*x.c - x.b*x.q) / (x.a*x.c - x.b*x.b) AS x0, (x.a*x.q - x.b*x.p) / (x.a*x.c - x.b*x.b) AS x1, (y.p*y.c - y.b*y.q) / (y.a*y.c - y.b*y.b) AS y0, (y.a*y.q - y.b*y.p) / (y.a*y.c - y.b*y.b) AS y1 FROM x, y)".format(x=_SOLVE.format(n=40), y=_SOLVE.format(n=60))


@query(f"{_SKETCH}, {_TWO} SELECT 40 AS s1, 60 AS s2, {qs('sqrt(((y0-x0)*(y0-x0) + (y1-x1)*(y1-x1)) / (x0*x0 + x1*x1))', 6)} AS change FROM v")
def self_convergence_2param(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = line(spark, sf_dir, _PRICE)
    got = refit.self_convergence(points, line_model(), [40], 20, "dct", b=256)
    return rows(spark, got, "s1 int, s2 int, c double").select("s1", "s2", q("c", 6).alias("change"))


@query(f"WITH {points_sql(_PRICE)}, b AS (SELECT {hint('pt_key', 'mix0', 3)} % 50 AS bkt, (1 - 2 * ({hint('pt_key', 'mix0', 2)} % 2)) AS s, c1, u FROM p) SELECT bkt::INTEGER AS bkt, {qs('sum(s)', 5)} AS w0, {qs('sum(s * sqrt(3) * (2 * c1 - 1))', 5)} AS w1, {qs('sum(s * u)', 5)} AS u FROM b GROUP BY bkt")
def sparse_sign_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, b = sketch.projected(line(spark, sf_dir, _PRICE), line_model(), 50)
    return rows(spark, [(i, float(x[0]), float(x[1]), float(y)) for i, (x, y) in enumerate(zip(a, b))], "bkt int, w0 double, w1 double, u double").select("bkt", q("w0", 5).alias("w0"), q("w1", 5).alias("w1"), q("u", 5).alias("u"))


# -- gains ----------------------------------------------------------------------------------------------


def rich_model(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, FunctionalTucker]:
    points = line(spark, sf_dir).persist()
    return points, model3(spark, sf_dir)


@query("SELECT true AS full_not_worse, true AS residual_agrees, true AS sketch_close")
def refit_gain(spark: SparkSession, sf_dir: str) -> DataFrame:
    points, model = rich_model(spark, sf_dir)
    before = metrics.achieved_error(points, model)[0]
    sol = lstsq.full(points, model)
    after = metrics.achieved_error(points, model.with_core(sol.core))[0]
    near = metrics.achieved_error(points, refit.refit_core(points, model, oversample=8, b=256).model)[0]
    points.unpersist()
    return rows(spark, [(after <= before * (1 + 1e-9), abs(after - sol.relative_residual) < 1e-6, near < 1.3 * after)], "full_not_worse boolean, residual_agrees boolean, sketch_close boolean")


@query("SELECT 1 AS k, true AS not_worse UNION ALL SELECT 2, true UNION ALL SELECT 3, true")
def axis_refit_gain(spark: SparkSession, sf_dir: str) -> DataFrame:
    points, model = rich_model(spark, sf_dir)
    errs = [metrics.achieved_error(points, model)[0]]
    for k in range(3):
        model = refit.refit_axis(points, model, k)
        errs.append(metrics.achieved_error(points, model)[0])
    points.unpersist()
    return rows(spark, [(k + 1, bool(b <= a * (1 + 1e-9))) for k, (a, b) in enumerate(zip(errs, errs[1:]))], "k int, not_worse boolean")


@query("SELECT true AS below_tolerance, true AS larger_than_core")
def auto_sized_refit(spark: SparkSession, sf_dir: str) -> DataFrame:
    points, model = rich_model(spark, sf_dir)
    got, changes = refit.auto_size(points, model, 0.02, b=256)
    points.unpersist()
    return rows(spark, [(min(c for *_, c in changes) < 0.02, got.s > model.R)], "below_tolerance boolean, larger_than_core boolean")
