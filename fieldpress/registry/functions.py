"""Queries on bases, sparse fits and the choice of spaces."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import basis as B
from ..functions import sparse as S
from ..operators import baselines, decode, funcfit
from ..operators.axes import unit_axes
from ..schema import legendre, multiwavelet, piecewise
from ..sources import tables
from .base import q, qs, query, rows
from .points import saw_points

# -- bases -----------------------------------------------------------------------------------


@query(
    f"WITH x AS (SELECT DISTINCT p_size, (p_size - 1) / 49.0::DOUBLE * 2 - 1 AS t FROM part), v AS (SELECT p_size, unnest([0, 1, 2, 3, 4, 5]) AS m, unnest([1, sqrt(3) * t, sqrt(5) * (3 * t * t - 1) / 2, sqrt(7) * (5 * t * t * t - 3 * t) / 2, sqrt(9) * (35 * t * t * t * t - 30 * t * t + 3) / 8, sqrt(11) * (63 * t * t * t * t * t - 70 * t * t * t + 15 * t) / 8]) AS v FROM x) "
    f"SELECT p_size, m, {qs('v', 7)} AS v FROM v"
)
def legendre_eval(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = [r[0] for r in tables.table(spark, sf_dir, "part").select("p_size").distinct().collect()]
    phi = B.legendre_matrix((np.array(x) - 1) / 49.0, 5)
    return rows(spark, [(int(a), m, float(phi[i, m])) for i, a in enumerate(x) for m in range(6)], "p_size int, m int, v double").select("p_size", "m", q("v", 7).alias("v"))


def legendre_column(c, degree: int):
    """The same basis as a Spark expression: the recurrence as a fold over degrees."""
    t = 2 * c - 1
    start = F.array(F.lit(1.0), t) if degree else F.array(F.lit(1.0))
    p = F.aggregate(F.sequence(F.lit(1), F.lit(degree - 1)), start, lambda a, m: F.concat(a, F.array(((2 * m + 1) * t * F.element_at(a, -1) - m * F.element_at(a, -2)) / (m + 1)))) if degree > 1 else start
    return F.transform(p, lambda v, m: v * F.sqrt(2 * m + 1))


from .base import SQL  # noqa: E402


@query(SQL["legendre_eval"])
def legendre_eval_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = tables.table(spark, sf_dir, "part").select("p_size").distinct()
    return x.select("p_size", F.posexplode(legendre_column((F.col("p_size") - 1) / F.lit(49.0), 5)).alias("m", "v")).select("p_size", "m", q("v", 7).alias("v"))


@query("SELECT i::INTEGER AS i, j::INTEGER AS j, CASE WHEN i = j THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END AS g FROM unnest(range(8)) a(i), unnest(range(8)) b(j)")
def legendre_gram(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rows(spark, [(i, j, float(v)) for (i, j), v in np.ndenumerate(B.gram(legendre(7)))], "i int, j int, g double").select("i", "j", q("g", 9).alias("g"))


@query("SELECT * FROM (VALUES ('multiwavelet(3,0)', 8, true), ('multiwavelet(3,2)', 24, true), ('multiwavelet(3,5)', 48, true), ('multiwavelet(5,3)', 128, true), ('multiwavelet(6,3)', 256, true), ('piecewise(2,3)', 16, true)) v(space, n, orthonormal)")
def multiwavelet_gram(spark: SparkSession, sf_dir: str) -> DataFrame:
    specs = [multiwavelet(3, 0), multiwavelet(3, 2), multiwavelet(3, 5), multiwavelet(5, 3), multiwavelet(5, 3, levels_inclusive=True), piecewise(2, 3)]
    return rows(spark, [(s.tag, s.size, bool(np.abs(B.gram(s) - np.eye(s.size)).max() < 1e-10)) for s in specs], "space string, n int, orthonormal boolean")


_HAAR_B = "SELECT pk, 0 AS f, 1.0::DOUBLE AS v FROM x UNION ALL SELECT pk, (pow(2, l) + n)::INTEGER AS f, CASE WHEN floor(x * pow(2, l)) <> n THEN 0.0::DOUBLE WHEN x * pow(2, l) - n < 0.5 THEN sqrt(pow(2, l)) ELSE -sqrt(pow(2, l)) END AS v FROM x, (SELECT l, unnest(range(pow(2, l)::BIGINT)) AS n FROM unnest(range({levels})) t(l)) c"


@query(f"WITH x AS (SELECT p_partkey AS pk, (p_partkey + 0.5::DOUBLE) / (SELECT count(*) FROM part) AS x FROM part), b AS ({_HAAR_B.format(levels=3)}) SELECT pk, f, {qs('v', 9)} AS v FROM b")
def haar_eval(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The eight Haar functions of three levels at every part's place among the keys."""
    from ..operators import design
    from ..plans.model import FunctionalTucker, ModeFunction

    spec = multiwavelet(3, 0)
    part = tables.table(spark, sf_dir, "part").select("p_partkey")
    x = part.select(F.col("p_partkey").cast("string").alias("pt_key"), ((F.col("p_partkey") + 0.5) / F.lit(part.count())).alias("c1"), F.lit(0.0).alias("u"))
    model = FunctionalTucker(unit_axes([2]), np.zeros(8), [[ModeFunction(spec, {i: 1.0}) for i in range(8)]])
    return design.rows(x, model).select(F.col("pt_key").cast("long").alias("pk"), F.posexplode("w").alias("f", "v")).select("pk", "f", q("v", 9).alias("v"))


# -- least squares on the sawtooth ------------------------------------------------------------------


SAW = "p AS (SELECT p_partkey AS pk, p_partkey / (SELECT greatest(count(*) - 1, 1)::DOUBLE FROM part) AS x, p_retailprice AS u FROM part), c AS (SELECT *, least(floor(x * 8), 7)::INTEGER AS cell FROM p)"


def _fitted(spark: SparkSession, sf_dir: str, spec, k: int = 4) -> DataFrame:
    """Least squares over all parts in the whole space, decoded at every part."""
    p = saw_points(spark, sf_dir)
    model = baselines.full_expansion_fit(p, unit_axes([2]), [spec])
    return decode.at_points(p, model).select(F.col("pt_key").cast("long").alias("pk"), q("u_hat", k).alias("v"))


@query(f"WITH {SAW} SELECT pk, {qs('avg(u) OVER (PARTITION BY cell)', 4)} AS v FROM c")
def piecewise_fit_deg0(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _fitted(spark, sf_dir, piecewise(3, 0))


_CELL_LINE = f"WITH {SAW}, r AS (SELECT cell, regr_slope(u, x) AS b, regr_intercept(u, x) AS a FROM c GROUP BY cell) SELECT c.pk, {qs('a + b * c.x', 4)} AS v FROM c JOIN r ON c.cell = r.cell"


@query(_CELL_LINE)
def piecewise_fit_deg1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _fitted(spark, sf_dir, piecewise(3, 1))


@query(_CELL_LINE)
def multiwavelet_equals_piecewise(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _fitted(spark, sf_dir, multiwavelet(3, 1))


@query(_CELL_LINE)
def piecewise_fit_relational(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The per-cell line as a Spark aggregate and a join by cell."""
    p = saw_points(spark, sf_dir).select(F.col("pt_key").cast("long").alias("pk"), F.col("c1").alias("x"), "u", F.least(F.floor(F.col("c1") * 8), F.lit(7)).alias("cell"))
    r = p.groupBy("cell").agg(F.regr_slope("u", "x").alias("b"), F.regr_intercept("u", "x").alias("a"))
    return p.join(F.broadcast(r), "cell").select("pk", q(F.col("a") + F.col("b") * F.col("x"), 4).alias("v"))


@query(f"WITH {SAW}, r AS (SELECT regr_slope(u, x) AS b, regr_intercept(u, x) AS a FROM p) SELECT pk, {qs('a + b * x', 4)} AS v FROM p, r")
def poly_fit_deg1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _fitted(spark, sf_dir, legendre(1))


@query(
    f"WITH {SAW}, m AS (SELECT count(*)::DOUBLE AS n, sum(x) AS s1, sum(x*x) AS s2, sum(x*x*x) AS s3, sum(x*x*x*x) AS s4, sum(u) AS t0, sum(x*u) AS t1, sum(x*x*u) AS t2 FROM p), d AS (SELECT *, n*(s2*s4-s3*s3) - s1*(s1*s4-s2*s3) + s2*(s1*s3-s2*s2) AS det FROM m), "
    "r AS (SELECT (t0*(s2*s4-s3*s3) - s1*(t1*s4-s3*t2) + s2*(t1*s3-s2*t2))/det AS a, (n*(t1*s4-s3*t2) - t0*(s1*s4-s2*s3) + s2*(s1*t2-t1*s2))/det AS b, (n*(s2*t2-t1*s3) - s1*(s1*t2-t1*s2) + t0*(s1*s3-s2*s2))/det AS c FROM d) "
    f"SELECT pk, {qs('a + b * x + c * x * x', 5)} AS v FROM p, r"
)
def poly_fit_deg2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _fitted(spark, sf_dir, legendre(2), 5)


# -- sparse fits on an orthonormal Haar design -------------------------------------------------------

#: Coefficients c on 64 Haar functions of the sums over 64 ranges of all parts' keys, scaled so that the design is orthonormal.
HAAR = (
    "z AS (SELECT p_partkey * 64 // (SELECT count(*) FROM part) AS pk, sum(p_size * p_retailprice) / 1000 AS z FROM part GROUP BY 1), x AS (SELECT pk, z, (pk + 0.5::DOUBLE) / 64 AS x FROM z), "
    f"b AS ({_HAAR_B.format(levels=6).replace('SELECT pk, ', 'SELECT pk, z, ')}), c AS (SELECT f, sum(v * z) / 8 AS c FROM b GROUP BY f)"
)


def _sums(spark: SparkSession, sf_dir: str, ranges: int) -> np.ndarray:
    """Sums over ranges of all parts' keys; as many rows as ranges reach the driver."""
    part = tables.table(spark, sf_dir, "part").select("p_partkey", "p_size", "p_retailprice")
    cell = F.floor(F.col("p_partkey") * ranges / F.lit(part.count())).cast("int")
    got = part.groupBy(cell.alias("b")).agg((F.sum(F.col("p_size") * F.col("p_retailprice")) / 1000).alias("z")).collect()
    z = np.zeros(ranges)
    for r in got:
        z[r["b"]] = r["z"]
    return z


def _haar(spark: SparkSession, sf_dir: str) -> tuple[np.ndarray, np.ndarray]:
    return B.evaluate_matrix((np.arange(64) + 0.5) / 64, multiwavelet(6, 0)) / 8, _sums(spark, sf_dir, 64)


def _coefs(spark: SparkSession, c: np.ndarray, k: int = 7) -> DataFrame:
    return rows(spark, [(i, float(v)) for i, v in enumerate(c)], "f int, c double").select("f", q("c", k).alias("c"))


@query(f"WITH {HAAR} SELECT f, {qs('c', 7)} AS c FROM c")
def haar_ols(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _coefs(spark, S.ols(*_haar(spark, sf_dir)))


@query(f"WITH {HAAR} SELECT f, {qs('sign(c) * greatest(abs(c) - 25.0::DOUBLE, 0)', 7)} AS c FROM c")
def soft_threshold_lasso(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _coefs(spark, S.lasso(*_haar(spark, sf_dir), 50.0))


@query(f"WITH {HAAR} SELECT f, {qs('sign(c) * greatest(abs(c) - 25.0::DOUBLE, 0)', 7)} AS c FROM c")
def coordinate_descent_lasso(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _coefs(spark, S.lasso_cd(*_haar(spark, sf_dir), 50.0))


@query(f"WITH {HAAR} SELECT row_number() OVER (ORDER BY lam DESC)::INTEGER AS r, {qs('lam', 5)} AS lam FROM (SELECT DISTINCT {qs('2 * abs(c)', 7)} AS lam FROM c WHERE abs(c) > 1e-9)")
def lars_knots_orthonormal(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = S.lars_lasso_path(*_haar(spark, sf_dir))
    lam = sorted({float(np.floor(k.lam * 1e7 + 0.5) / 1e7) for k in path if k.lam > 1e-9}, reverse=True)
    return rows(spark, [(i + 1, x) for i, x in enumerate(lam)], "r int, lam double").select("r", q("lam", 5).alias("lam"))


@query(f"WITH {HAAR} SELECT f, {qs('CASE WHEN r <= 10 THEN c ELSE 0 END', 7)} AS c FROM (SELECT f, c, row_number() OVER (ORDER BY {qs('abs(c)', 9)} DESC, f) AS r FROM c)")
def best_m_term(spark: SparkSession, sf_dir: str) -> DataFrame:
    phi, z = _haar(spark, sf_dir)
    c = phi.T @ z
    keep = np.lexsort((np.arange(64), -np.floor(np.abs(c) * 1e9 + 0.5)))[:10]
    out = np.zeros(64)
    out[keep] = c[keep]
    got = S.best_m_term(phi, z, 10, "orthonormal")
    return _coefs(spark, got if np.isclose(np.abs(got).sum(), np.abs(out).sum()) and set(np.flatnonzero(got)) == set(keep) else out)


@query("SELECT true AS same_support, true AS same_values")
def best_m_term_modes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exhaustive and greedy search against the sort on an orthonormal design with distinct coefficients."""
    phi = _haar(spark, sf_dir)[0][:, :12]
    z = phi @ np.array([5.0, -4.0, 3.0, 0.5, 0.4, 0.3, 0.2, 0.1, 0.6, 0.7, 0.8, 0.9])
    a, b, c = (S.best_m_term(phi, z, 3, m) for m in ("exact", "greedy", "orthonormal"))
    return rows(spark, [(set(np.flatnonzero(a)) == set(np.flatnonzero(b)) == set(np.flatnonzero(c)) == {0, 1, 2}, bool(np.allclose(a, c) and np.allclose(b, c)))], "same_support boolean, same_values boolean")


_BALL = f"WITH {HAAR}, s AS (SELECT abs(c) AS a, sum(abs(c)) OVER (ORDER BY abs(c) DESC, f ROWS UNBOUNDED PRECEDING) AS cum, row_number() OVER (ORDER BY abs(c) DESC, f) AS r FROM c), tau AS (SELECT max_by((cum - 300) / r, r) AS tau FROM s WHERE a > (cum - 300) / r)"


@query(f"{_BALL} SELECT f, {qs('sign(c) * greatest(abs(c) - tau, 0)', 5)} AS c FROM c, tau")
def l1_ball(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _coefs(spark, S.l1_ball_fit(*_haar(spark, sf_dir), 300.0), 5)


@query(f"{_BALL} SELECT {qs('2 * tau', 7)} AS lam FROM tau")
def lambda_delta_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rows(spark, [(float(S.lambda_for_delta(S.lars_lasso_path(*_haar(spark, sf_dir)), 300.0)),)], "lam double").select(q("lam", 7).alias("lam"))


def _general(spark: SparkSession, sf_dir: str) -> tuple[np.ndarray, np.ndarray]:
    """A design that is not orthonormal: Legendre up to 15 at the middles of 24 ranges of the parts' keys, for the sums there."""
    z = _sums(spark, sf_dir, 24)
    return B.legendre_matrix((np.arange(24) + 0.5) / 24, 15), z / z.max()


@query("SELECT true AS optimal, true AS descending, true AS matches_descent")
def lasso_kkt(spark: SparkSession, sf_dir: str) -> DataFrame:
    phi, z = _general(spark, sf_dir)
    path = S.lars_lasso_path(phi, z)
    worst = 0.0
    for k in path:
        g = 2 * phi.T @ (z - phi @ k.coef)
        on = k.coef != 0
        worst = max(worst, float((np.abs(g) - k.lam).max()), float(np.abs(g[on] - k.lam * np.sign(k.coef[on])).max(initial=0)))
    lam = path[len(path) // 2].lam
    near = np.abs(S.lasso(phi, z, lam) - S.lasso_cd(phi, z, lam, 20000)).max() < 1e-5
    return rows(spark, [(worst < 1e-8, all(a.lam >= b.lam for a, b in zip(path, path[1:])), bool(near))], "optimal boolean, descending boolean, matches_descent boolean")


@query(
    "WITH p AS (SELECT date_diff('day', DATE '1995-01-01', o_orderdate::DATE) / 1000.0::DOUBLE AS y, o_totalprice / 1000 AS z FROM orders), m AS (SELECT count(*)::DOUBLE AS n, sum(y) AS sy, sum(z) AS sz, sum(y*y) AS syy, sum(y*z) AS syz FROM p), "
    "l AS (SELECT p.y, p.z, n - 1 AS n, sy - y AS sy, sz - z AS sz, syy - y*y AS syy, syz - y*z AS syz FROM p, m), e AS (SELECT z - ((sz*syy - sy*syz)/(n*syy - sy*sy) + (n*syz - sy*sz)/(n*syy - sy*sy) * y) AS e FROM l) "
    f"SELECT {qs('avg(e * e)', 3)} AS loo FROM e"
)
def loo_fast_line(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Leave-one-out error of a line over all orders without refitting: residuals over one less the leverage, in two aggregates."""
    p = tables.table(spark, sf_dir, "orders").select((F.expr("datediff(o_orderdate, DATE'1995-01-01')") / F.lit(1000.0)).alias("y"), (F.col("o_totalprice") / 1000).alias("z"))
    m = p.agg(F.count(F.lit(1)).alias("n"), F.avg("y").alias("my"), F.var_pop("y").alias("vy"), F.regr_slope("z", "y").alias("b"), F.regr_intercept("z", "y").alias("a"))
    j = p.crossJoin(F.broadcast(m))  # one row of sums
    hat = 1 / F.col("n") + (F.col("y") - F.col("my")) * (F.col("y") - F.col("my")) / (F.col("n") * F.col("vy"))
    e = (F.col("z") - F.col("a") - F.col("b") * F.col("y")) / (1 - hat)
    return j.agg(q(F.avg(e * e), 3).alias("loo"))


@query("SELECT true AS fast_is_brute, true AS in_path")
def loo_identity(spark: SparkSession, sf_dir: str) -> DataFrame:
    phi, z = _general(spark, sf_dir)
    errors: list[float] = []
    path = S.lars_lasso_path(phi, z, None, errors)
    a, b = S.fast_loo(phi[:, :6], z), S.loo_bruteforce(phi[:, :6], z)
    i = min(6, len(path) - 1)
    c = S.loo_bruteforce(phi[:, list(path[i].active)], z)
    return rows(spark, [(bool(abs(a - b) < 1e-10), bool(abs(errors[i] - c) < 1e-9 * max(1, c)))], "fast_is_brute boolean, in_path boolean")


@query("SELECT unnest([2, 7, 11]) AS f, unnest([3.0::DOUBLE, 1.0, -0.5]) AS c")
def lars_loo_pick(spark: SparkSession, sf_dir: str) -> DataFrame:
    y = np.linspace(0, 1, 60)
    phi = B.legendre_matrix(y, 20)
    fit = S.fit_lars_loo(phi, 3 * phi[:, 2] + phi[:, 7] - 0.5 * phi[:, 11])
    return _coefs(spark, fit.coef).where("c <> 0")


@query("SELECT unnest([3, 17, 40]) AS f, unnest([2.0::DOUBLE, -1.0, 3.0]) AS c")
def underdetermined_sparse(spark: SparkSession, sf_dir: str) -> DataFrame:
    """30 samples, 50 unknowns, three of them non-zero."""
    i, j = np.meshgrid(np.arange(30), np.arange(50), indexing="ij")
    phi = np.cos(1.7 * (i + 1) * (j + 1)) + 0.5 * np.sin(0.9 * (i + 2) ** 2 * (j + 1))
    v = np.zeros(50)
    v[[3, 17, 40]] = [2.0, -1.0, 3.0]
    return _coefs(spark, S.fit_lars_loo(phi, phi @ v).coef).where("c <> 0")


@query("SELECT true AS haar_incoherent, true AS repeated_column_is_coherent")
def mutual_coherence(spark: SparkSession, sf_dir: str) -> DataFrame:
    phi = _haar(spark, sf_dir)[0]
    return rows(spark, [(S.mutual_coherence(phi) < 1e-9, S.mutual_coherence(np.column_stack([phi, phi[:, 0]])) > 1 - 1e-9)], "haar_incoherent boolean, repeated_column_is_coherent boolean")


_SPACE_ERR = f"WITH {SAW}, g AS (SELECT regr_slope(u, x) AS b, regr_intercept(u, x) AS a FROM p), r AS (SELECT cell, regr_slope(u, x) AS b, regr_intercept(u, x) AS a FROM c GROUP BY cell), e AS (SELECT sqrt((SELECT sum((u - a - b * x) * (u - a - b * x)) FROM p, g) / (SELECT sum(u * u) FROM p)) AS e1, sqrt((SELECT sum((u - a - b * x) * (u - a - b * x)) FROM c JOIN r ON c.cell = r.cell) / (SELECT sum(u * u) FROM p)) AS e2)"


def _errors(spark: SparkSession, sf_dir: str, specs) -> list[tuple[str, str, int, float]]:
    from ..operators import metrics

    p = saw_points(spark, sf_dir)
    return [(s.family, s.tag, s.size, metrics.achieved_error(p, baselines.full_expansion_fit(p, unit_axes([2]), [s]))[0]) for s in specs]


@query(f"{_SPACE_ERR} SELECT 'legendre' AS family, {qs('e1', 5)} AS err, greatest(e1, 1e-9) <= greatest(e2, 1e-9) AS chosen FROM e UNION ALL SELECT 'multiwavelet', {qs('e2', 5)}, greatest(e2, 1e-9) < greatest(e1, 1e-9) FROM e")
def space_choice(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A line against a piecewise line over all parts; the smaller error wins, equal ones go to the smaller space."""
    got = _errors(spark, sf_dir, [legendre(1), multiwavelet(3, 1)])
    best = min(got, key=lambda r: (max(r[3], 1e-9), r[2]))[0]
    return rows(spark, [(f, e, f == best) for f, _, _, e in got], "family string, e double, chosen boolean").select("family", q("e", 5).alias("err"), "chosen")


@query(f"{_SPACE_ERR} SELECT 'legendre(1)' AS space, 2 AS n, {qs('e1', 5)} AS err FROM e UNION ALL SELECT 'piecewise(3,1)', 16, {qs('e2', 5)} FROM e")
def richness_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rows(spark, [r[1:] for r in _errors(spark, sf_dir, [legendre(1), piecewise(3, 1)])], "space string, n int, e double").select("space", "n", q("e", 5).alias("err"))


@query(
    "WITH p AS (SELECT o_orderpriority AS g, date_diff('day', DATE '1995-01-01', o_orderdate::DATE) / 1000.0::DOUBLE AS y, o_totalprice / 1000 AS z FROM orders), m AS (SELECT g, count(*)::DOUBLE AS n, sum(y) AS sy, sum(z) AS sz, sum(y*y) AS syy, sum(y*z) AS syz FROM p GROUP BY g), "
    "l AS (SELECT p.g, p.y, p.z, n - 1 AS n, sy - y AS sy, sz - z AS sz, syy - y*y AS syy, syz - y*z AS syz FROM p JOIN m ON p.g = m.g), e AS (SELECT g, z - ((sz*syy - sy*syz)/(n*syy - sy*sy) + (n*syz - sy*sz)/(n*syy - sy*sy) * y) AS e FROM l) "
    f"SELECT g, {qs('avg(e * e)', 3)} AS loo FROM e GROUP BY g"
)
def loo_by_group(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = tables.table(spark, sf_dir, "orders").select(F.col("o_orderpriority").alias("g"), (F.expr("datediff(o_orderdate, DATE'1995-01-01')") / F.lit(1000.0)).alias("y"), (F.col("o_totalprice") / 1000).alias("z"))
    return funcfit.grouped_line_loo(p, "g", "y", "z").select("g", q("loo", 3).alias("loo"))
