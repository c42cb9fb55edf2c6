"""The engine on Spark: edge cases, invariants, plans, surfaces and streams."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from fieldpress.functions import basis as B
from fieldpress.functions import mixers
from fieldpress.operators import axes as AX
from fieldpress.operators import baselines, decode, design, funcfit, lstsq, metrics, mixing, regrid, sampling, sketch, tucker
from fieldpress.operators import tensor_ops as ops
from fieldpress.plans import refit
from fieldpress.plans.compress import compress
from fieldpress.plans.model import FunctionalTucker, ModeFunction
from fieldpress.schema import FieldSpec, indices, legendre, multiwavelet, points_schema
from fieldpress.sources import tables


def make_points(spark, f, n=2000, d=3, seed=0):
    rng = np.random.default_rng(seed)
    c = rng.random((n, d))
    rows = [(str(i), *map(float, x), float(f(*x))) for i, x in enumerate(c)]
    return spark.createDataFrame(rows, points_schema(d))


def two_by_two():
    one, lin = ModeFunction(legendre(1), {0: 1.0}), ModeFunction(legendre(1), {1: 1.0})
    return FunctionalTucker(AX.unit_axes([5, 5]), np.array([[1.0, 2.0], [3.0, -1.0]]), [[one, lin], [one, lin]])


def field(x, y):
    return two_by_two().evaluate([np.array([x]), np.array([y])])[0]


# -- points and axes ------------------------------------------------------------------------


def test_null_and_nan_points_are_dropped_and_counted(spark):
    df = spark.createDataFrame([(1, 0.5, 1.0), (2, None, 1.0), (3, float("nan"), 1.0), (4, 0.1, None)], "id int, x double, v double")
    spec = FieldSpec({"x": "x"}, "v", ("id",))
    assert [r.pt_key for r in tables.build_points(df, spec).collect()] == ["1"]
    assert tables.clean_counts(df, spec).first().asDict() == {"kept": 1, "n_null": 2, "n_nan": 1}


def test_one_level_axis_and_empty_table(spark):
    p = spark.createDataFrame([("a", 2.0, 0.0, 5.0), ("b", 2.0, 1.0, 7.0)], points_schema(2))
    axes = AX.fit_axes(p, [5, 3])
    assert axes[0].nodes == 1 and axes[1].nodes == 3
    t = {(r.i1, r.i2): r.v for r in regrid.tent_average(p, axes).collect()}
    assert t == {(0, 0): 5.0, (0, 2): 7.0}
    empty = p.where("false")
    assert AX.fit_axes(empty, [5, 3])[0].lo == 0.0
    assert regrid.local_linear(empty, AX.unit_axes([3, 3])).count() == 0
    assert regrid.fill_holes(regrid.nearest(empty, AX.unit_axes([3, 3])), AX.unit_axes([3, 3])).count() == 0


def test_hash_sample_does_not_depend_on_partitions(spark):
    p = make_points(spark, lambda *x: 0.0)
    a, b = (sorted(r.pt_key for r in sampling.hash_fraction(p.repartition(n), 0.3).collect()) for n in (1, 7))
    assert a == b and 450 < len(a) < 750


# -- regridding ----------------------------------------------------------------------------------


@pytest.mark.parametrize("d", [1, 2, 3, 4])
def test_local_linear_reproduces_affine_fields(spark, d):
    w = np.arange(1, d + 1)
    p = make_points(spark, lambda *x: 1 + float(w @ np.array(x)), 3000, d)
    axes = AX.unit_axes([3] * d)
    for r in regrid.local_linear(p, axes, ridge=0.0, adaptive=False).collect():
        y = np.array([r[i] / 2 for i in indices(d)])
        assert r.v == pytest.approx(1 + w @ y, abs=1e-6)


@pytest.mark.parametrize("held", [10, 400_000])
def test_fused_moments_are_those_of_the_columns(spark, held):
    for d in (1, 2, 3):
        p = make_points(spark, lambda *x: sum(x) ** 2, 700, d).repartition(3)
        axes = AX.unit_axes([4] * d) if d > 1 else AX.unit_axes([1])
        a, b = ({tuple(r[i] for i in indices(d)): r for r in f(p, axes).collect()} for f in (lambda x, y: regrid.fused_moments(x, y, held), regrid.node_moments))
        assert a.keys() == b.keys()
        for k in a:
            for n in a[k].asDict():
                assert a[k][n] == pytest.approx(b[k][n], abs=1e-9)


def test_points_on_the_right_boundary_and_duplicates(spark):
    p = spark.createDataFrame([("a", 1.0, 3.0), ("b", 1.0, 5.0), ("c", 0.0, 1.0)], points_schema(1))
    t = {r.i1: (r.v, r.support) for r in regrid.tent_average(p, AX.unit_axes([4])).collect()}
    assert t == {3: (4.0, 2.0), 0: (1.0, 1.0)}


def test_fill_holes_reaches_every_node(spark):
    p = spark.createDataFrame([("a", 0.0, 0.0, 3.0)], points_schema(2))
    axes = AX.unit_axes([4, 5])
    full = regrid.fill_holes(regrid.nearest(p, axes), axes)
    assert full.count() == 20 and {r.v for r in full.collect()} == {3.0}
    assert regrid.fill_holes(regrid.nearest(p, axes), axes, "mean").count() == 20


# -- tensors --------------------------------------------------------------------------------------


def test_distributed_decomposition_is_the_local_one(spark):
    rng = np.random.default_rng(0)
    x = rng.random((6, 5, 4)) + 3
    t = ops.from_numpy(spark, x)
    for kw in ({"eps": 0.05}, {"ranks": [2, 3, 2]}, {"eps": 0.05, "mode_order": "largest"}):
        a, b = tucker.st_hosvd(t, [6, 5, 4], **kw), tucker.st_hosvd(t, [6, 5, 4], **kw, local_cells=0)
        assert a.ranks == b.ranks and np.allclose(a.core, b.core) and a.discarded == pytest.approx(b.discarded, abs=1e-8)
        gap = np.linalg.norm(x - tucker.expand(a.core, a.factors)) ** 2
        assert gap == pytest.approx(a.discarded, abs=1e-9)
    c = tucker.t_hosvd(t, [6, 5, 4], 0.05, local_cells=0)
    assert np.linalg.norm(x - tucker.expand(c.core, c.factors)) <= 0.05 * np.linalg.norm(x)
    assert tucker.relative_error(t, tucker.reconstruct(spark, a), 3) <= 0.05 * 1.0001


def test_zero_and_constant_tensors(spark):
    z = tucker.numpy_st_hosvd(np.zeros((3, 4)), 1e-2)
    assert z.ranks == (1, 1) and z.error == 0
    assert tucker.numpy_st_hosvd(np.full((3, 4, 2), 7.0), 1e-6).ranks == (1, 1, 1)
    with pytest.raises(ValueError):
        tucker.numpy_st_hosvd(np.ones((2, 2)), None, None)


# -- functions and compression ----------------------------------------------------------------------


def test_space_choice_never_interpolates(spark):
    x = np.linspace(0, 1, 20)
    samples = spark.createDataFrame([(1, 1, x.tolist(), np.sin(3 * x).tolist()), (2, 1, [0.0], [1.0])], funcfit.SAMPLES)
    rows = funcfit.fit_all(samples, [legendre(40), multiwavelet(5, 3)]).collect()
    assert all(r.n < 20 for r in rows) and {r.k for r in rows} == {1, 2}


def test_compress_then_decode_a_product_field(spark):
    p = make_points(spark, lambda x, y, z: (1 + x) * (2 - y) * (1 + z))
    axes = AX.unit_axes([8, 8, 8])
    model = compress(p, axes, 1e-3, candidates=[legendre(3)])
    assert metrics.achieved_error(p, model)[0] < 0.05
    better = refit.refit_full(p, model)
    assert metrics.achieved_error(p, better)[0] <= metrics.achieved_error(p, model)[0] * (1 + 1e-9) + 1e-12
    alt = refit.alternate(p, model)
    assert metrics.achieved_error(p, alt)[0] <= metrics.achieved_error(p, better)[0] * (1 + 1e-6) + 1e-12
    r = metrics.report(p, model)
    assert r["ratio_values"] > 0 and r["nnz"] == model.nnz


def test_results_do_not_depend_on_partitions(spark):
    p = make_points(spark, field, 1500, 2)
    found = []
    for n in (1, 4, 7):
        q = p.repartition(n)
        found.append((lstsq.full(q, two_by_two()).core, refit.refit_core(q, two_by_two(), 20, b=64).model.core.ravel(), np.array(sorted(x.lev for x in sketch.leverage(q, two_by_two()).collect()))))
    for other in found[1:]:
        for a, b in zip(found[0], other):
            assert np.allclose(a, b, atol=1e-9)


# -- least squares and sketches -----------------------------------------------------------------------


@pytest.mark.parametrize("method", ["gram", "tsqr"])
def test_full_least_squares_recovers_the_core(spark, method):
    p = make_points(spark, field, 500, 2)
    s = lstsq.full(p, two_by_two(), method)
    assert np.allclose(s.core, [1, 2, 3, -1]) and s.rows == 500 and s.relative_residual < 1e-6
    none = lstsq.full(p.where("false"), two_by_two(), method)
    assert none.rows == 0 and none.underdetermined


@pytest.mark.parametrize("mix", ["dft", "dct", "wht", "none", "gauss", "sparse_sign"])
def test_sketches_solve_exact_fields(spark, mix):
    p = make_points(spark, field, 700, 2)
    got = refit.refit_core(p, two_by_two(), 30, mix=mix, b=64)
    assert np.allclose(got.model.core.ravel(), [1, 2, 3, -1], atol=1e-6) and not got.underdetermined


def test_short_and_long_sketches(spark):
    p = make_points(spark, field, 60, 2)
    short = refit.refit_core(p, two_by_two(), 2, b=16)
    assert short.underdetermined and np.isfinite(short.model.core).all()
    assert refit.refit_core(p, two_by_two(), 500, b=16).s == 60  # no more rows than points


def test_leverage_sums_to_rank_before_and_after_mixing(spark):
    p = make_points(spark, lambda x, y: x * y, 640, 2)
    lev = sketch.leverage(p, two_by_two())
    assert lev.agg(F.sum("lev")).first()[0] == pytest.approx(4)
    for kind in ("dft", "dct", "wht"):
        m = sketch.mixed_leverage(p, two_by_two(), kind, 64)
        assert m.agg(F.sum("lev")).first()[0] == pytest.approx(4)


def test_partition_blocks_need_no_shuffle(spark):
    p = make_points(spark, field, 300, 2).repartition(3)
    rows = sketch.mixed_rows(p, two_by_two(), float("inf"), "dct", 50, scope="partition")
    assert rows.groupBy("blk").count().agg(F.max("count")).first()[0] <= 50 and rows.count() == 300
    plan = sketch.mixed_rows(spark.read.parquet("/root/testdata/sf0.001/lineitem.parquet").selectExpr("cast(l_orderkey as string) pt_key", "l_tax c1", "l_discount c2", "l_quantity u"), two_by_two(), 0.5, scope="partition")._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan
    with pytest.raises(ValueError):
        sketch.mixed_rows(p, two_by_two(), 0.5, scope="other")


def test_a_block_a_core_and_panels_add_up(spark, monkeypatch):
    monkeypatch.setattr(lstsq, "PANEL", 7)
    df = spark.range(0, 2000, 1, 200)
    make = lambda batches: sum((np.full((5, 3), float(b.num_rows)) for b in batches), np.zeros((5, 3)))
    cores = spark.sparkContext.defaultParallelism
    assert lstsq.panels(df, make).count() <= cores * 3  # 15 numbers are three panels
    assert (lstsq.sum_blocks(df, make, (5, 3)) == 2000).all()
    assert lstsq.sum_blocks(df, lambda batches: None, (5, 3)) is None
    stacked = lstsq.merge_blocks(df, lambda batches: np.array([[float(sum(b.num_rows for b in batches))]]), lambda a, b: a + b, 1)
    assert stacked.tolist() == [[2000.0]]


def test_cores_beyond_the_driver(spark):
    """Conjugate gradients over the points and over a stored sketch against dense solutions."""
    rng = np.random.default_rng(4)
    p = spark.createDataFrame([(str(i), *map(float, rng.random(2) ** 2), float(rng.normal())) for i in range(3000)], "pt_key string, c1 double, c2 double, u double")
    m = FunctionalTucker(AX.unit_axes([9, 9]), np.zeros((9, 7)), [[ModeFunction(legendre(n - 1), {i: 1.0}) for i in range(n)] for n in (9, 7)])
    dense = lstsq.full(p, m)
    got = lstsq.full(p, m, max_r=1)
    assert got.converged and np.abs(got.core - dense.core).max() < 1e-6 and got.residual2 == pytest.approx(dense.residual2, rel=1e-6)
    few = lstsq.lsqr(p, m, rounds=2)
    assert not few.converged and few.rounds == 2
    share = 200 / 3000
    rows = sketch.mixed_rows(p, m, share, b=256, total=3000).toArrow()
    w = rows.column("row").combine_chunks().flatten().to_numpy().reshape(-1, m.R + 1)
    want = np.linalg.lstsq(w[:, :-1], w[:, -1], rcond=None)[0]
    kept = sketch.solve_sketch(p, m, 200, b=256, total=3000, max_bytes=0)
    assert kept.rows == len(w) and np.abs(kept.core - want).max() < 1e-5


def test_global_rows_are_one_transform(spark):
    p = make_points(spark, field, 500, 2)
    m = two_by_two()
    a, b = sketch.global_rows(p, m, 40, length=64)
    t = mixing.numbered(mixing.signs(p)).orderBy("q").toPandas()
    assert t["q"].tolist() == list(range(500))
    q2 = -(-500 // 64)
    q = -(-500 // q2) * q2
    w = np.zeros((q, m.R + 1))
    w[:500] = np.column_stack([m.design([t["c1"].to_numpy(), t["c2"].to_numpy()]), t["u"].to_numpy()]) * t["sgn"].to_numpy()[:, None]
    want = mixers.mix(w, "dft")[sketch.global_outputs(p, q, 40)]
    assert np.abs(np.column_stack([a, b]) - want).max() < 1e-9


def test_fill_holes_is_complete_from_one_node(spark):
    axes = AX.unit_axes([40, 30, 10])
    t = spark.createDataFrame([(3, 4, 5, 2.5, 1.0)], "i1 int, i2 int, i3 int, v double, support double")
    full = regrid.fill_holes(t, axes)
    assert full.count() == 12000 and full.where("v <> 2.5 OR v IS NULL").count() == 0


def test_sums_of_a_stream_survive_a_restart(spark, tmp_path):
    """Two runs of one stream, the second with more files: the core is that of all points."""
    from fieldpress.streaming import refresh

    p = make_points(spark, field, 400, 2)
    src, where, sums = (str(tmp_path / x) for x in ("src", "checkpoint", "sums"))
    m, seen = two_by_two(), []
    parts = [p.where(F.pmod(F.xxhash64("pt_key"), F.lit(3)) == i) for i in range(3)]
    for run, some in enumerate((parts[:2], parts[2:])):
        for i, part in enumerate(some):
            part.coalesce(1).write.mode("append").parquet(src)
        stream = spark.readStream.schema(p.schema).option("maxFilesPerTrigger", 1).parquet(src)
        refresh.refresh_each_batch(stream, m, lambda model, n: seen.append((model.core.ravel(), n)), where, sums).awaitTermination()
    assert seen[-1][1] == 400 and len(seen) == 3
    assert np.abs(seen[-1][0] - lstsq.full(p, m).core).max() < 1e-9


def test_model_as_json(spark):
    m = two_by_two()
    back = FunctionalTucker.from_json(m.to_json())
    x = [np.linspace(0, 1, 9)] * 2
    assert np.allclose(back.evaluate(x), m.evaluate(x)) and back.axes == m.axes


def test_large_cores_are_refused_by_the_dense_solver(spark):
    big = FunctionalTucker(AX.unit_axes([3, 3]), np.zeros((100, 100)), [[ModeFunction(legendre(0), {0: 1.0})] * 100] * 2)
    with pytest.raises(ValueError, match="refit_top"):
        lstsq.moments(make_points(spark, field, 5, 2), big)


# -- decoding and surfaces ---------------------------------------------------------------------------


def test_decode_handles_nulls_and_extra_columns(spark):
    df = spark.createDataFrame([("x", 0.5, 0.5), ("y", None, 0.5)], "name string, c1 double, c2 double")
    r = {x.name: x.u_hat for x in decode.at_points(df, two_by_two()).collect()}
    assert r["x"] == pytest.approx(1.0) and r["y"] is None


def test_box_mean_is_the_mean_of_decoded_values(spark):
    m = two_by_two()
    box = decode.box(spark, m, {"c1": (0.2, 0.6), "c2": (0.1, 0.4)}, [401, 301])
    assert decode.box_mean(m, {"c1": (0.2, 0.6), "c2": (0.1, 0.4)}) == pytest.approx(box.agg(F.avg("u_hat")).first()[0], abs=1e-6)


def test_bundle_and_data_source(spark, tmp_path):
    from fieldpress.sources import datasource

    m = two_by_two()
    m.save(spark, str(tmp_path / "m"))
    back = FunctionalTucker.load(spark, str(tmp_path / "m"))
    assert np.allclose(back.core, m.core) and back.functions[0][1].basis == legendre(1)
    pushed = datasource.read(spark, str(tmp_path / "m"), nodes="11,5")
    plain = spark.read.format("fieldpress").option("nodes", "11,5").load(str(tmp_path / "m"))
    for df in (pushed, plain):
        got = sorted((r.c1, r.u_hat) for r in df.where("c1 > 0.55 AND c2 = 0.5").collect())
        assert [round(x, 6) for x, _ in got] == [0.6, 0.7, 0.8, 0.9, 1.0]
        for x, v in got:
            assert v == pytest.approx(field(x, 0.5))


def test_sql_functions(spark):
    from fieldpress.operators import sql_surface

    sql_surface.register(spark, two_by_two(), "_t")
    assert spark.sql("SELECT fp_decode_t(0.5D, 0.5D)").first()[0] == pytest.approx(1.0)
    assert spark.sql("SELECT count(*) FROM fp_slice_t('c1', 0.5D, 7)").first()[0] == 7
    w = spark.sql("SELECT sum(w), count(*) FROM fp_corners_t(1.25D, 2.5D)").first()
    assert w[0] == pytest.approx(1.0) and w[1] == 4


def test_baselines(spark):
    p = make_points(spark, field, 500, 2)
    full = baselines.full_expansion_fit(p, AX.unit_axes([5, 5]), [legendre(1), legendre(1)])
    assert np.allclose(full.core.ravel(), [1, 2, 3, -1])
    q = baselines.quantise_summary(baselines.block_quantise(p, AX.unit_axes([5, 5]), 10), 500)
    assert q["error"] < 1e-2 and q["cells"] == 16


# -- plans -----------------------------------------------------------------------------------------------


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_scans_are_pruned(spark, sf):
    text = plan(tables.line_points(spark, sf))
    assert "l_tax" not in text and "l_returnflag" not in text and "l_shipdate" in text and "Exchange" not in text


def test_decode_and_design_do_not_shuffle(spark):
    p = make_points(spark, field, 50, 2)
    assert "Exchange" not in plan(decode.at_points(p, two_by_two()))
    assert "Exchange" not in plan(design.rows(p, two_by_two()))


def test_regrid_combines_before_the_shuffle(spark):
    text = plan(regrid.node_moments(make_points(spark, field, 50, 2), AX.unit_axes([4, 4])))
    assert "partial_sum" in text and text.count("Exchange") <= 2 and "CartesianProduct" not in text


# -- streams -----------------------------------------------------------------------------------------------


def test_stateful_refit_of_a_stream(spark, tmp_path):
    from fieldpress.streaming import refresh

    p = make_points(spark, field, 400, 2)
    p.repartition(3).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(p.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    out = refresh.refresh_core(stream, two_by_two(), shards=2)
    q = out.writeStream.format("memory").queryName("blocks").outputMode("update").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    model = refresh.solve_blocks(spark.table("blocks"), two_by_two())
    assert np.allclose(model.core.ravel(), [1, 2, 3, -1])


def test_stream_moments_equal_batch(spark, tmp_path):
    from fieldpress.streaming import refresh

    p = make_points(spark, field, 300, 2)
    p.repartition(3).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(p.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    axes = AX.unit_axes([4, 4])
    q = refresh.regrid_moments(stream, axes).writeStream.format("memory").queryName("moments").outputMode("complete").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    a = {(r.i1, r.i2): r.v for r in regrid.from_moments(spark.table("moments"), 2).collect()}
    b = {(r.i1, r.i2): r.v for r in regrid.local_linear(p, axes).collect()}
    assert a.keys() == b.keys() and all(a[k] == pytest.approx(b[k], abs=1e-8) for k in a)


def test_late_events_are_dropped(spark, tmp_path):
    from fieldpress.streaming import refresh

    (tmp_path / "in").mkdir()
    e = spark.sql("SELECT 1L event_id, TIMESTAMP_NTZ'2024-01-01 10:00:00' ts, 1L user_id, 'a' event_type, 1.0D value")
    e.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    source = spark.readStream.schema(e.schema).parquet(str(tmp_path / "in"))

    def run():
        q = refresh.windowed(source, size="1 hour", delay="1 hour").writeStream.format("parquet").option("path", str(tmp_path / "out")).outputMode("append").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True)
        q.start().awaitTermination()
        return sorted(r.n for r in spark.read.schema("n long, start timestamp").parquet(str(tmp_path / "out")).collect())

    run()
    spark.sql("SELECT 2L event_id, TIMESTAMP_NTZ'2024-01-01 20:00:00' ts, 1L user_id, 'a' event_type, 1.0D value").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    first = run()
    spark.sql("SELECT 3L event_id, TIMESTAMP_NTZ'2024-01-01 10:30:00' ts, 1L user_id, 'a' event_type, 1.0D value").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    assert first == [1] and run() == [1]  # the late event opens no window


def test_polynomial_columns_match_numpy(spark):
    from fieldpress.registry.functions import legendre_column

    got = spark.range(5).select(legendre_column(F.col("id") / 4.0, 6).alias("v")).collect()
    want = B.legendre_matrix(np.arange(5) / 4.0, 6)
    assert np.allclose([r.v for r in got], want)
