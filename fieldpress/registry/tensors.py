"""Queries on tensors and their decompositions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import baselines, metrics, regrid, tucker
from ..operators import tensor_ops as ops
from ..schema import indices
from ..sources import tables
from .base import q, qs, query, rows
from .points import CUBE_AXES, REVENUE, revenue_cells

# -- fixtures ---------------------------------------------------------------------------

COUNT_DIMS = [3, 5, 11]


def count_tensor(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts of lineitem by return flag (3), quantity tenth (5) and discount (11)."""
    flag = F.when(F.col("l_returnflag") == "A", 0).when(F.col("l_returnflag") == "N", 1).otherwise(2)
    cells = tables.table(spark, sf_dir, "lineitem").select(flag.cast("int").alias("i1"), F.floor((F.col("l_quantity") - 1) / 10).cast("int").alias("i2"), F.floor(F.col("l_discount") * 100 + 0.5).cast("int").alias("i3"))
    return cells.groupBy(*indices(3)).agg(F.count(F.lit(1)).cast("double").alias("v"))


COUNTS = "t AS (SELECT CASE l_returnflag WHEN 'A' THEN 0 WHEN 'N' THEN 1 ELSE 2 END AS i1, floor((l_quantity - 1) / 10)::INTEGER AS i2, floor(l_discount * 100 + 0.5)::INTEGER AS i3, count(*)::DOUBLE AS v FROM lineitem GROUP BY 1, 2, 3)"

CHARGE_DIMS = [50, 11, 9]


def level_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """i1, i2, i3, x1, x2, x3: the grid of the levels of quantity, discount and tax in the table, a cross of three small dictionaries."""
    t = tables.table(spark, sf_dir, "lineitem")

    def levels(c: str, i: str) -> DataFrame:
        d = t.select(F.col(c).alias(f"x{i}")).distinct()
        return d.select(f"x{i}", (F.row_number().over(Window.orderBy(f"x{i}")) - 1).cast("int").alias(f"i{i}"))

    return levels("l_quantity", "1").crossJoin(F.broadcast(levels("l_discount", "2"))).crossJoin(F.broadcast(levels("l_tax", "3")))


def charge_tensor(spark: SparkSession, sf_dir: str) -> DataFrame:
    """quantity (1 - discount)(1 + tax) on the grid of levels."""
    return level_grid(spark, sf_dir).select(*indices(3), (F.col("x1") * (1 - F.col("x2")) * (1 + F.col("x3"))).alias("v"))


CHARGE = "lv AS (SELECT DISTINCT l_quantity AS x FROM lineitem), ld AS (SELECT DISTINCT l_discount AS x FROM lineitem), lt AS (SELECT DISTINCT l_tax AS x FROM lineitem), c AS (SELECT a.i1, b.i2, t.i3, a.x * (1 - b.x) * (1 + t.x) AS v FROM (SELECT x, (row_number() OVER (ORDER BY x) - 1)::INTEGER AS i1 FROM lv) a, (SELECT x, (row_number() OVER (ORDER BY x) - 1)::INTEGER AS i2 FROM ld) b, (SELECT x, (row_number() OVER (ORDER BY x) - 1)::INTEGER AS i3 FROM lt) t)"


def front_of_levels(spark: SparkSession, sf_dir: str) -> np.ndarray:
    """The moving front on the grid of levels, each axis scaled to [0, 1]."""
    c = level_grid(spark, sf_dir).withColumns({"c1": (F.col("x1") - 1) / 49, "c2": F.col("x2") / 0.1, "c3": F.col("x3") / 0.08})
    return ops.to_numpy(c.select(*indices(3), F.expr(tables.FRONT3).cast("double").alias("v")), CHARGE_DIMS)


def embedding_matrix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("int").alias("i1"), F.posexplode("embedding").alias("i2", "v")).select("i1", "i2", F.col("v").cast("double").alias("v"))


def planted(spark: SparkSession, expr: str, dims: list[int]) -> DataFrame:
    """A closed form of c1..c3 on the nodes of a unit grid."""
    from ..operators.axes import unit_axes

    g = regrid.grid(spark, unit_axes(dims))
    c = g.select("*", *[(F.col(f"i{k}") / F.lit(float(n - 1))).alias(f"c{k}") for k, n in enumerate(dims, 1)])
    return c.select(*indices(3), F.expr(expr).cast("double").alias("v"))


# -- algebra ------------------------------------------------------------------------------


@query(f"WITH {COUNTS}, g AS (SELECT i1::INTEGER AS i1, i2::INTEGER AS i2, i3::INTEGER AS i3 FROM unnest(range(3)) a(i1), unnest(range(5)) b(i2), unnest(range(11)) c(i3)) SELECT (g.i1 * 11 + g.i3)::BIGINT AS rest, g.i2 AS i, coalesce(t.v, 0) AS v FROM g LEFT JOIN t ON g.i1 = t.i1 AND g.i2 = t.i2 AND g.i3 = t.i3")
def tensor_unfold(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ops.fibers(count_tensor(spark, sf_dir), COUNT_DIMS, 1).select("rest", F.posexplode("vec").alias("i", "v"))


def _gram_sql(k: int) -> str:
    me = f"i{k}"
    other = [f"x.i{m} = y.i{m}" for m in (1, 2, 3) if m != k]
    return f"SELECT {k} AS k, x.{me} AS a, y.{me} AS b, sum(x.v * y.v) AS g FROM t x JOIN t y ON {' AND '.join(other)} AND x.{me} <= y.{me} GROUP BY x.{me}, y.{me}"


_GRAMS = f"WITH {COUNTS} " + " UNION ALL ".join(_gram_sql(k) for k in (1, 2, 3))


@query(_GRAMS)
def mode_gram(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = count_tensor(spark, sf_dir)
    out = None
    for k, n in enumerate(COUNT_DIMS):
        g = ops.partial_grams(ops.fibers(t, COUNT_DIMS, k), n).where("g <> 0").select(F.lit(k + 1).alias("k"), "a", "b", "g")
        out = g if out is None else out.union(g)
    return out


@query(_GRAMS)
def mode_gram_relational(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = count_tensor(spark, sf_dir)
    out = None
    for k in range(3):
        g = ops.gram_sql(t, COUNT_DIMS, k).select(F.lit(k + 1).alias("k"), "a", "b", "g")
        out = g if out is None else out.union(g)
    return out


@query(f"WITH {COUNTS} SELECT sum(v * v) AS norm2, count(*)::BIGINT AS cells FROM t")
def frobenius_norm(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = count_tensor(spark, sf_dir)
    return rows(spark, [(ops.norm2(t), t.count())], "norm2 double, cells long")


_M = np.array([[1.0, 0.0], [2.0, -1.0], [0.5, 3.0]])
_MSQL = "m(i, j, w) AS (VALUES (0, 0, 1.0::DOUBLE), (0, 1, 0.0::DOUBLE), (1, 0, 2.0::DOUBLE), (1, 1, -1.0::DOUBLE), (2, 0, 0.5::DOUBLE), (2, 1, 3.0::DOUBLE))"
_PRODUCT_SQL = f"WITH {COUNTS}, {_MSQL} SELECT m.j AS i1, t.i2, t.i3, sum(t.v * m.w) AS v FROM t JOIN m ON t.i1 = m.i GROUP BY m.j, t.i2, t.i3"


@query(_PRODUCT_SQL)
def mode_product(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ops.mode_product(count_tensor(spark, sf_dir), COUNT_DIMS, _M, 0)


@query(_PRODUCT_SQL)
def mode_product_relational(spark: SparkSession, sf_dir: str) -> DataFrame:
    factor = rows(spark, [(i, j, float(w)) for (i, j), w in np.ndenumerate(_M)], "i int, j int, w double")
    return ops.mode_product_sql(count_tensor(spark, sf_dir), factor, 0, 3)


@query("SELECT 0 AS pt, sum(v * b) AS value FROM (VALUES (1.0::DOUBLE, 2.0::DOUBLE), (3.0, 0.5), (-1.0, 4.0)) x(v, b)")
def tensor_inner(spark: SparkSession, sf_dir: str) -> DataFrame:
    coefs = rows(spark, [(0, 0, 1.0), (0, 1, 3.0), (1, 0, -1.0)], "i1 int, i2 int, v double")
    basis = rows(spark, [("0", 0, 0, 2.0), ("0", 0, 1, 0.5), ("0", 1, 0, 4.0)], "pt_key string, i1 int, i2 int, b double")
    return ops.inner(coefs, basis, 2).select(F.col("pt_key").cast("int").alias("pt"), "value")


# -- spectra ---------------------------------------------------------------------------------


def _by_rest(sql_level: str) -> str:
    return f"x AS (SELECT {sql_level} AS i, date_trunc('month', l_shipdate) AS m, count(*)::DOUBLE AS v FROM lineitem GROUP BY 1, 2), g AS (SELECT a.i AS a, b.i AS b, sum(a.v * b.v) AS g FROM x a JOIN x b ON a.m = b.m GROUP BY a.i, b.i)"


def _levels(spark: SparkSession, sf_dir: str, column: str, levels: list[str]) -> DataFrame:
    i = F.lit(0)
    for n, x in enumerate(levels):
        i = F.when(F.col(column) == x, F.lit(n)).otherwise(i)
    month = F.expr("(year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1")
    return tables.table(spark, sf_dir, "lineitem").select(i.cast("int").alias("i1"), month.cast("int").alias("i2")).groupBy("i1", "i2").agg(F.count(F.lit(1)).cast("double").alias("v"))


def _sigmas(spark: SparkSession, t: DataFrame, n: int) -> DataFrame:
    s = tucker.st_hosvd(t, [n, 96], eps=1e-14).spectra[0]
    return rows(spark, [(i + 1, float(x)) for i, x in enumerate(np.sqrt(s))], "j int, sigma double").select("j", q("sigma", 5).alias("sigma"))


@query(f"WITH {_by_rest('CASE l_linestatus WHEN ' + chr(39) + 'F' + chr(39) + ' THEN 0 ELSE 1 END')}, e AS (SELECT max(CASE WHEN a = 0 AND b = 0 THEN g END) AS a, max(CASE WHEN a = 1 AND b = 1 THEN g END) AS c, coalesce(max(CASE WHEN a = 0 AND b = 1 THEN g END), 0) AS b FROM g) SELECT 1 AS j, {qs('sqrt((a + c) / 2 + sqrt(((a - c) / 2) * ((a - c) / 2) + b * b))', 5)} AS sigma FROM e UNION ALL SELECT 2, {qs('sqrt((a * c - b * b) / ((a + c) / 2 + sqrt(((a - c) / 2) * ((a - c) / 2) + b * b)))', 5)} FROM e")
def two_level_svd(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sigmas(spark, _levels(spark, sf_dir, "l_linestatus", ["F", "O"]), 2)


_E3 = "e AS (SELECT " + ", ".join(f"coalesce(max(CASE WHEN a = {a} AND b = {b} THEN g END), 0) AS g{a}{b}" for a in range(3) for b in range(a, 3)) + " FROM g), m AS (SELECT *, (g00 + g11 + g22) / 3 AS m FROM e), n AS (SELECT *, sqrt(((g00 - m) * (g00 - m) + (g11 - m) * (g11 - m) + (g22 - m) * (g22 - m) + 2 * (g01 * g01 + g02 * g02 + g12 * g12)) / 6) AS p FROM m), o AS (SELECT *, acos(greatest(-1.0::DOUBLE, least(1.0::DOUBLE, ((g00 - m) * ((g11 - m) * (g22 - m) - g12 * g12) - g01 * (g01 * (g22 - m) - g12 * g02) + g02 * (g01 * g12 - (g11 - m) * g02)) / (2 * p * p * p)))) / 3 AS phi FROM n)"


@query(f"WITH {_by_rest('CASE l_returnflag WHEN ' + chr(39) + 'A' + chr(39) + ' THEN 0 WHEN ' + chr(39) + 'N' + chr(39) + ' THEN 1 ELSE 2 END')}, {_E3} SELECT j, {qs('sqrt(lam)', 3)} AS sigma FROM (SELECT 1 AS j, m + 2 * p * cos(phi) AS lam FROM o UNION ALL SELECT 3, m + 2 * p * cos(phi + 2 * pi() / 3) FROM o UNION ALL SELECT 2, m + 2 * p * cos(phi + 4 * pi() / 3) FROM o)")
def three_level_svd(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sigmas(spark, _levels(spark, sf_dir, "l_returnflag", ["A", "N", "R"]), 3).select("j", q("sigma", 3).alias("sigma"))


_SQUARE = "{b} AS (SELECT x.i, y.j, sum(x.g * y.g) AS g FROM (SELECT i, j, g / (SELECT sum(g) FROM {a} WHERE i = j) AS g FROM {a}) x JOIN (SELECT i, j, g / (SELECT sum(g) FROM {a} WHERE i = j) AS g FROM {a}) y ON x.j = y.i GROUP BY x.i, y.j)"


@query(
    f"WITH {COUNTS}, g0 AS (SELECT x.i3 AS i, y.i3 AS j, sum(x.v * y.v) AS g FROM t x JOIN t y ON x.i1 = y.i1 AND x.i2 = y.i2 GROUP BY x.i3, y.i3), "
    + ", ".join(_SQUARE.format(a=f"g{k}", b=f"g{k + 1}") for k in range(6))
    + f" SELECT {qs('sqrt((SELECT sum(x.g * y.g) FROM g0 x JOIN g6 y ON x.i = y.j AND x.j = y.i) / (SELECT sum(g) FROM g6 WHERE i = j))', 4)} AS sigma"
)
def leading_sigma_power(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = tucker.st_hosvd(count_tensor(spark, sf_dir), COUNT_DIMS, ranks=COUNT_DIMS, mode_order=[2, 0, 1]).spectra[2]
    return rows(spark, [(float(np.sqrt(s[0])),)], "sigma double").select(q("sigma", 4).alias("sigma"))


@query("SELECT * FROM (VALUES ('affine', 2, 2, 2), ('charge', 1, 1, 1), ('constant', 1, 1, 1), ('product', 1, 1, 1), ('quadratic', 2, 2, 3), ('separable_sum', 3, 3, 3)) v(name, r1, r2, r3)")
def sthosvd_rank_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = []
    for name in ("constant", "affine", "product", "quadratic", "separable_sum"):
        r = tucker.st_hosvd(planted(spark, tables.ELEVEN[name], [12, 10, 8]), [12, 10, 8], eps=1e-6).ranks
        out.append((name, *map(int, r)))
    charge = charge_tensor(spark, sf_dir)
    dims = [r[0] + 1 for r in (charge.agg(F.max("i1")).first(), charge.agg(F.max("i2")).first(), charge.agg(F.max("i3")).first())]
    out.append(("charge", *map(int, tucker.st_hosvd(charge, dims, eps=1e-6).ranks)))
    return rows(spark, out, "name string, r1 int, r2 int, r3 int")


@query("SELECT eps, true AS within FROM (VALUES (1e-1::DOUBLE), (1e-2::DOUBLE), (1e-3::DOUBLE)) v(eps)")
def sthosvd_within_eps(spark: SparkSession, sf_dir: str) -> DataFrame:
    cube = regrid.cumulative_cube(revenue_cells(spark, sf_dir), CUBE_AXES)
    array = ops.to_numpy(cube, [101, 50, 11])
    out = []
    for eps in (1e-1, 1e-2, 1e-3):
        r = tucker.numpy_st_hosvd(array, eps)
        gap = float(np.linalg.norm(array - tucker.expand(r.core, r.factors)) / np.linalg.norm(array))
        out.append((eps, gap <= eps * (1 + 1e-9)))
    return rows(spark, out, "eps double, within boolean")


@query("SELECT true AS monotone, true AS below_grid")
def sthosvd_rank_monotone(spark: SparkSession, sf_dir: str) -> DataFrame:
    dims = [24, 24, 12]
    array = ops.to_numpy(planted(spark, tables.FRONT3, dims), dims)
    ranks = [tucker.numpy_st_hosvd(array, e).ranks for e in (1e-1, 1e-2, 1e-3, 1e-4)]
    return rows(spark, [(all(a[0] <= b[0] for a, b in zip(ranks, ranks[1:])), all(r <= n for x in ranks for r, n in zip(x, dims)))], "monotone boolean, below_grid boolean")


@query(f"WITH {CHARGE} SELECT {qs('sum(v * v)', 1)} AS norm2, {qs('sum(v * v)', 1)} AS split FROM c")
def sthosvd_norm_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = tucker.st_hosvd(charge_tensor(spark, sf_dir), CHARGE_DIMS, eps=1e-3)
    return rows(spark, [(r.norm2, float((r.core**2).sum()) + r.discarded)], "a double, b double").select(q("a", 1).alias("norm2"), q("b", 1).alias("split"))


@query("SELECT * FROM (VALUES ('sequential', true), ('classical', true)) v(method, within)")
def thosvd_vs_sthosvd(spark: SparkSession, sf_dir: str) -> DataFrame:
    cube = regrid.cumulative_cube(revenue_cells(spark, sf_dir), CUBE_AXES)
    dims, eps = [101, 50, 11], 1e-2
    array = ops.to_numpy(cube, dims)
    out = []
    for name, r in (("sequential", tucker.numpy_st_hosvd(array, eps)), ("classical", tucker.t_hosvd(ops.from_numpy(spark, array), dims, eps))):
        out.append((name, bool(np.linalg.norm(array - tucker.expand(r.core, r.factors)) <= eps * np.linalg.norm(array) * (1 + 1e-9))))
    return rows(spark, out, "method string, within boolean")


@query("SELECT 3::INTEGER AS modes, true AS same_ranks, true AS same_core")
def sthosvd_distributed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The shuffled decomposition against the driver's on the same tensor."""
    dims = [12, 10, 8]
    t = planted(spark, tables.FRONT3, dims)
    a, b = tucker.st_hosvd(t, dims, 1e-2), tucker.st_hosvd(t, dims, 1e-2, local_cells=0)
    return rows(spark, [(len(dims), a.ranks == b.ranks, bool(a.ranks == b.ranks and np.allclose(a.core, b.core, atol=1e-8)))], "modes int, same_ranks boolean, same_core boolean")


@query("SELECT (8 * (1 + (SELECT count(DISTINCT l_quantity) FROM lineitem) + (SELECT count(DISTINCT l_discount) FROM lineitem) + (SELECT count(DISTINCT l_tax) FROM lineitem)))::BIGINT AS bytes")
def dense_tucker_storage(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rows(spark, [(baselines.dense_tucker(charge_tensor(spark, sf_dir), CHARGE_DIMS, 1e-6).bytes,)], "bytes long")


@query(f"WITH {CHARGE} SELECT i1, i2, i3, {qs('v', 6)} AS v FROM c")
def tensor_reconstruct(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = tucker.st_hosvd(charge_tensor(spark, sf_dir), CHARGE_DIMS, eps=1e-7)
    return tucker.reconstruct(spark, r).select(*indices(3), q("v", 6).alias("v"))


@query(f"WITH x AS (SELECT unnest(embedding)::DOUBLE AS v FROM embeddings) SELECT {qs('sum(v * v)', 6)} AS energy, true AS descending, true AS flat FROM x")
def embeddings_svd_energy(spark: SparkSession, sf_dir: str) -> DataFrame:
    m = embedding_matrix(spark, sf_dir)
    n = m.agg(F.max("i1")).first()[0] + 1
    # the short side's Gram matrix is enough
    s = tucker.eigen(ops.gram(ops.fibers(m, [n, 64], 1), 64))[0]
    return rows(spark, [(float(s.sum()), bool((np.diff(s) <= 1e-12).all()), bool(s[:10].sum() < 0.5 * s.sum()))], "e double, descending boolean, flat boolean").select(q("e").alias("energy"), "descending", "flat")


@query(f"WITH w AS (SELECT l_returnflag AS f, sum(l_quantity) / (SELECT sum(l_quantity) FROM lineitem) AS w FROM lineitem GROUP BY 1) SELECT (row_number() OVER (ORDER BY w DESC))::INTEGER AS rank, {qs('w')} AS abs_core, {qs('sum(w * w) OVER (ORDER BY w DESC ROWS UNBOUNDED PRECEDING) / sum(w * w) OVER ()', 9)} AS cum_energy FROM w")
def core_decay(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three orthogonal Haar terms, weighted by the return flags' shares of the quantity: the core holds those weights."""
    q_ = tables.table(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.sum("l_quantity").alias("w")).orderBy("l_returnflag").collect()
    h = np.array([[1, 1, 1, 1], [1, 1, -1, -1], [1, -1, 0, 0]]) / np.array([[2.0], [2.0], [np.sqrt(2)]])
    t = sum(r["w"] * np.einsum("i,j,k->ijk", v, v, v) for r, v in zip(q_, h)) / sum(r["w"] for r in q_)
    core = tucker.numpy_st_hosvd(t, 1e-6).core
    df = rows(spark, [([int(i) + 1 for i in j], float(v)) for j, v in np.ndenumerate(core)], "j array<int>, v double")
    return metrics.core_decay(df).where("abs_core > 1e-6").select("rank", q("abs_core").alias("abs_core"), q("cum_energy", 9).alias("cum_energy"))


@query("SELECT least(n1, n2 * n3)::INTEGER AS r1, least(n2, n1 * n3)::INTEGER AS r2, least(n3, n1 * n2)::INTEGER AS r3 FROM (SELECT count(DISTINCT l_quantity) AS n1, count(DISTINCT floor(l_discount * 100 + 0.5)) AS n2, count(DISTINCT least(floor((p_retailprice - 900) / 5), 19)) AS n3 FROM lineitem JOIN part ON l_partkey = p_partkey)")
def noise_control(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean raw price by quantity, discount and retail bucket does not compress: every rank is the number of levels (or of the other axes' cells, where that is less)."""
    part = tables.table(spark, sf_dir, "part").select("p_partkey", "p_retailprice")
    j = tables.table(spark, sf_dir, "lineitem").select("l_partkey", "l_quantity", "l_discount", "l_extendedprice").join(part, F.col("l_partkey") == F.col("p_partkey"))
    cells = j.select((F.col("l_quantity") - 1).cast("int").alias("i1"), F.floor(F.col("l_discount") * 100 + 0.5).cast("int").alias("i2"), F.least(F.floor((F.col("p_retailprice") - 900) / 5), F.lit(19)).cast("int").alias("i3"), "l_extendedprice")
    t = cells.groupBy(*indices(3)).agg(F.avg("l_extendedprice").alias("v"))
    r = tucker.st_hosvd(t, [50, 11, 20], eps=1e-4).ranks
    return rows(spark, [tuple(map(int, r))], "r1 int, r2 int, r3 int")


@query(f"WITH {REVENUE}, t AS (SELECT i2, sum(v) AS v FROM cells GROUP BY i2), r AS (SELECT row_number() OVER (ORDER BY v DESC, i2) AS rank, i2, v FROM t) SELECT rank::INTEGER AS rank, i2, {qs('v', 2)} AS v FROM r WHERE rank <= 10")
def topk_core(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ten largest entries of a one-axis marginal tensor: a limit by design."""
    t = revenue_cells(spark, sf_dir).groupBy("i2").agg(F.sum("v").alias("v"))
    top = t.orderBy(F.desc("v"), "i2").limit(10)
    return top.select(F.row_number().over(Window.orderBy(F.desc("v"), "i2")).alias("rank"), "i2", q("v", 2).alias("v"))


@query(f"WITH {COUNTS} SELECT rank::INTEGER AS rank, {qs('e', 9)} AS energy FROM (SELECT row_number() OVER (ORDER BY v DESC, i1, i2, i3) AS rank, sum(v * v) OVER (ORDER BY v DESC, i1, i2, i3 ROWS UNBOUNDED PRECEDING) / sum(v * v) OVER () AS e FROM t)")
def running_energy(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.orderBy(F.desc("v"), *indices(3))
    t = count_tensor(spark, sf_dir)
    total = F.sum(F.col("v") * F.col("v")).over(Window.partitionBy())
    return t.select(F.row_number().over(w).alias("rank"), q(F.sum(F.col("v") * F.col("v")).over(w.rowsBetween(Window.unboundedPreceding, 0)) / total, 9).alias("energy"))


# -- text tables as count tensors ------------------------------------------------------------------


def _length_bucket(c):
    return F.floor(F.log2(c + 1)).cast("int")


@query("SELECT lang, source, floor(log2(length(text) + 1))::INTEGER AS bucket, count(*)::BIGINT AS v FROM documents GROUP BY 1, 2, 3")
def doc_count_tensor(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.table(spark, sf_dir, "documents").groupBy("lang", "source", _length_bucket(F.length("text")).alias("bucket")).agg(F.count(F.lit(1)).alias("v"))


@query("SELECT role, turn, floor(log2(length(text) + 1))::INTEGER AS bucket, count(*)::BIGINT AS v FROM conversations GROUP BY 1, 2, 3")
def conversation_tensor(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.table(spark, sf_dir, "conversations").groupBy("role", "turn", _length_bucket(F.length("text")).alias("bucket")).agg(F.count(F.lit(1)).alias("v"))


@query("SELECT d.lang, l.quality, l.toxic, floor(log2(d.n_chars + 1))::INTEGER AS bucket, count(*)::BIGINT AS v FROM documents d JOIN labels l ON d.doc_id = l.doc_id GROUP BY 1, 2, 3, 4")
def label_tensor(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = tables.table(spark, sf_dir, "documents").select("doc_id", "lang", "n_chars")
    return d.join(tables.table(spark, sf_dir, "labels"), "doc_id").groupBy("lang", "quality", "toxic", _length_bucket(F.col("n_chars")).alias("bucket")).agg(F.count(F.lit(1)).alias("v"))


@query("SELECT regexp_extract(url, '://([^/]*)', 1) AS host, floor(log2(length(html) + 1))::INTEGER AS bucket, count(*)::BIGINT AS v FROM pages GROUP BY 1, 2")
def page_tensor(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.table(spark, sf_dir, "pages").groupBy(F.regexp_extract("url", "://([^/]*)", 1).alias("host"), _length_bucket(F.length("html")).alias("bucket")).agg(F.count(F.lit(1)).alias("v"))


@query("SELECT true AS within")
def doc_tensor_hosvd(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = doc_count_tensor(spark, sf_dir)
    a = t.select(F.dense_rank().over(Window.orderBy("lang")).alias("a"), F.dense_rank().over(Window.orderBy("source")).alias("b"), "bucket", "v")
    t3 = a.select((F.col("a") - 1).cast("int").alias("i1"), (F.col("b") - 1).cast("int").alias("i2"), F.col("bucket").alias("i3"), F.col("v").cast("double").alias("v"))
    dims = [r + 1 for r in t3.agg(F.max("i1"), F.max("i2"), F.max("i3")).first()]
    r = tucker.st_hosvd(t3, dims, 0.05)
    return rows(spark, [(bool(r.error <= 0.05),)], "within boolean")


