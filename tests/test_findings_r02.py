"""Cases that the second review found: sizes and rows on which a query left its SQL."""

import os
import threading

import numpy as np
import pytest
from pyspark.errors import AnalysisException

from fieldpress.functions import basis as B
from fieldpress.operators import lstsq, metrics, mixing, sketch
from fieldpress.operators.axes import unit_axes
from fieldpress.plans import refit
from fieldpress.plans.model import FunctionalTucker, ModeFunction
from fieldpress.registry import base, refits, reports
from fieldpress.schema import BasisSpec, legendre, multiwavelet
from fieldpress.sources import tables
from tests.test_registry import QUERIES, SQL, cell


def agree(spark, folder, name, **tables):
    """The query against its SQL on a folder of some tables (SQL that makes them)."""
    import duckdb

    c = duckdb.connect()
    for t, sql in tables.items():
        c.execute(f"copy ({sql}) to '{folder}/{t}.parquet'")
        c.execute(f"create view {t} as select * from '{folder}/{t}.parquet'")
    df = QUERIES[name](spark, str(folder))
    o = c.execute(SQL[name])
    names = [d[0] for d in o.description]
    assert sorted(names) == sorted(df.columns)
    key = lambda r: tuple((x is not None, str(x)) for x in r)
    a = sorted((tuple(cell(r[n]) for n in names) for r in df.collect()), key=key)
    b = sorted((tuple(cell(x) for x in r) for r in o.fetchall()), key=key)
    assert a == b
    return a


def of(sf, table):
    return os.path.join(sf, f"{table}.parquet")


def test_half_a_block_more_is_a_block_more(spark):
    points = spark.range(640).selectExpr("cast(id as string) as pt_key", "0D as c1")
    assert {r[0] for r in mixing.blocks(points, 256).select("blk").distinct().collect()} == {0, 1, 2}


@pytest.mark.parametrize("name", ["row_blocks", "uniform_rows", "leverage_mixing", "sketched_ls_2param", "self_convergence_2param", "self_convergence_curve", "oversampling_2param"])
def test_blocks_of_a_table_of_half_blocks(spark, sf, tmp_path, name):
    assert agree(spark, tmp_path, name, lineitem=f"select * from '{of(sf, 'lineitem')}' order by all limit 5760")  # 22.5 blocks of 256


EVENTS = "select event_id::BIGINT as event_id, (timestamp '2024-01-03 00:00:00' + to_microseconds(us)) as ts, 7::BIGINT as user_id, 'click' as event_type, event_id * 1.25::DOUBLE as value from (values (1, 0), (2, 400000), (3, 21600300000), (4, 21600900000), (5, 43199600000), (6, 43199500000), (7, 43199400000), (8, 43198500000)) v(event_id, us)"


def test_moving_mean_to_the_microsecond(spark, tmp_path):
    got = dict(agree(spark, tmp_path, "moving_mean_range", events=EVENTS))
    assert got[3] == (2 + 3) * 1.25 / 2  # the event 21,600.3 seconds before is out, the one 21,599.9 before is in


def test_sliding_windows_over_rounded_seconds(spark, tmp_path):
    agree(spark, tmp_path, "events_sliding", events=EVENTS)


@pytest.mark.parametrize("mix", ["none", "dft", "dct", "wht", "gauss", "sparse_sign"])
def test_several_sizes_from_one_sketch(spark, sf, mix):
    points, model = base.line(spark, sf).persist(), refits.literal_model()
    total = points.count()
    for s, got in zip((3, 12), refit.refit_sizes(points, model, [3, 12], mix, b=256, total=total)):
        alone = refit.refit_core(points, model, s, mix=mix, b=256, total=total)
        assert (got.s, got.underdetermined) == (alone.s, alone.underdetermined)
        assert np.allclose(got.model.core, alone.model.core, rtol=1e-9)
    points.unpersist()


def test_errors_of_several_cores(spark, sf):
    points, cores = base.line(spark, sf), [np.ones(4), np.array([1.0, 0.5, -2.0, 0.25])]
    alone = [metrics.achieved_error(points, refits.literal_model(c.reshape(2, 2, 1)))[0] for c in cores]
    assert np.allclose(metrics.core_errors(points, refits.literal_model(), cores), alone, rtol=1e-12)


@pytest.mark.parametrize("kind", ["dft", "wht"])
def test_blocks_without_a_draw_stay_out_of_the_shuffle(spark, sf, kind):
    points, model = base.line(spark, sf), refits.line_model()
    part = sketch.drawn_points(points, 3, 1, kind, 64, total=6000)
    assert 0 < part.count() < 3000
    rows = [sorted(map(tuple, sketch.mixed_rows(p, model, share, kind, 64, total=6000).where(f"h < {sketch.share_of(1, 6000)}").select("blk", "out", "h").collect())) for p, share in ((part, sketch.share_of(1, 6000)), (points, sketch.share_of(1, 6000)), (points, 0.5))]
    assert rows[0] == rows[1] == rows[2] and rows[0]


def test_reports_sketch_once_a_mixer(spark, sf, monkeypatch):
    made = []
    one = sketch.mixed_rows
    monkeypatch.setattr(sketch, "mixed_rows", lambda *a, **k: made.append(1) or one(*a, **k))
    assert len(QUERIES["oversampling_2param"](spark, sf).collect()) == 18
    assert len(made) == 3


def polynomials(*ranks):
    return FunctionalTucker(unit_axes([r + 2 for r in ranks]), np.zeros(ranks), [[ModeFunction(legendre(r - 1), {i: 1.0}) for i in range(r)] for r in ranks])


@pytest.mark.parametrize("ranks", [(4,), (3, 5), (4, 3, 2), (2, 3, 2, 4)])
@pytest.mark.parametrize("levels", [1, 7, None])
@pytest.mark.parametrize("limit", [40, 16_000_000])
def test_shared_rows_are_the_design_rows(ranks, levels, limit, monkeypatch):
    monkeypatch.setattr(lstsq, "SLICE", limit)
    rng, m = np.random.default_rng(1), polynomials(*ranks)
    cols = [rng.random(300) for _ in ranks]
    cols[-1] = cols[-1] if levels is None else rng.integers(0, levels, 300) / 8
    y, core, w = rng.normal(size=300), rng.normal(size=ranks), m.design(cols)
    shared = lstsq.SharedRows(m, cols)
    assert (shared.run is None) == (levels is None)
    assert np.allclose(shared.transposed(y).ravel(), w.T @ y)
    assert np.allclose(shared.values(core), w @ core.ravel())
    assert np.allclose(lstsq.unpaired(shared.transposed(np.ones(300), pairs=True), ranks), w.T @ w)


@pytest.mark.parametrize("spec", [legendre(0), legendre(1), legendre(37), multiwavelet(1, 3), multiwavelet(3, 3), multiwavelet(5, 1), multiwavelet(3, 0), BasisSpec("piecewise", 2, 2)])
def test_quick_sums_of_basis_functions(spec):
    rng = np.random.default_rng(2)
    x, coef = np.concatenate([np.arange(65) / 64, rng.random(500)]), rng.normal(size=(spec.size, 3))
    assert np.allclose(B.combine(x, spec, coef, step=100), B.evaluate_matrix(x, spec) @ coef, rtol=0, atol=1e-11)


def test_a_large_core_moves_only_different_sums(spark, sf, monkeypatch):
    """All points for 512 unknowns: the blocks that are summed are not of R x R numbers, and the Gram matrix is the design rows'."""
    moved, add = [], lstsq.sum_blocks
    monkeypatch.setattr(lstsq, "sum_blocks", lambda rows, make, shape: moved.append(int(np.prod(shape))) or add(rows, make, shape))
    points, m = base.line(spark, sf), polynomials(8, 8, 8)
    g, b, uu, n = lstsq.moments(points, m)
    assert moved[0] < m.R**2 / 4
    p = points.toPandas()
    w = m.design([p[c].to_numpy() for c in ("c1", "c2", "c3")])
    u = p["u"].to_numpy()
    assert n == len(p) and uu == pytest.approx(u @ u)
    assert np.allclose(g, w.T @ w, rtol=1e-9, atol=1e-6) and np.allclose(b, w.T @ u, rtol=1e-9, atol=1e-6)
    core = lstsq.solve_gram(g, b)[0]
    assert metrics.shared_error(points, m.with_core(core)) == pytest.approx(metrics.achieved_error(points, m.with_core(core))[0], rel=1e-9)


def test_rounds_read_repeated_coordinates_once(spark, sf, monkeypatch):
    kept, cut = [], lstsq.cut
    monkeypatch.setattr(lstsq, "cut", lambda df, tag: kept.append(cut(df, tag)) or kept[-1])
    counts, drop = [], lstsq.discard
    monkeypatch.setattr(lstsq, "discard", lambda df: counts.append((df.count(), df.agg({"n": "sum"}).first()[0])) or drop(df))
    points, m = base.line(spark, sf).persist(), polynomials(4, 3, 2)
    n = points.select("c1", "c2", "c3").distinct().count()
    copies = points.selectExpr("pt_key", "c1", "c2", "c3", "u").unionByName(points.selectExpr("pt_key", "c1", "c2", "c3", "u + 1 AS u")).unionByName(points.selectExpr("pt_key", "c1", "c2", "c3", "3 * u AS u"))
    for p in (copies, points):
        dense, got = lstsq.full(p, m), lstsq.full(p, m, max_r=1)
        assert got.converged and got.rows == p.count()
        assert np.abs(got.core - dense.core).max() < 1e-6 and got.residual2 == pytest.approx(dense.residual2, rel=1e-6)
    assert counts[0] == (n, copies.count())
    points.unpersist()


@pytest.mark.parametrize("direct", [64_000_000, 1])
def test_rounds_make_no_plan(spark, sf, monkeypatch, direct):
    """However many rounds, the tables are planned a fixed number of times; the tasks' sums add up on the driver and in a tree."""
    made, add = [], lstsq.sum_blocks
    monkeypatch.setattr(lstsq, "sum_blocks", lambda *a: made.append(1) or add(*a))
    monkeypatch.setattr(lstsq, "DIRECT", direct, raising=False)
    points, m = base.line(spark, sf).persist(), polynomials(4, 3, 2)
    got = lstsq.full(points, m, max_r=1)
    assert got.converged and got.rounds > 2 and len(made) == 2  # right side, Gram matrices of the axes
    assert np.abs(got.core - lstsq.full(points, m).core).max() < 1e-6
    points.unpersist()


def test_variables_run_beside_each_other(spark):
    """Two jobs that wait for each other both end, and the rows keep their order."""
    both = threading.Barrier(2, timeout=30)
    assert reports.together(spark, lambda x: (x, both.wait() >= 0, spark.range(3).count()), ["b", "a"]) == [("b", True, 3), ("a", True, 3)]


@pytest.mark.parametrize("name", ["axis_nodes", "canonical_view", "core_decay", "decay_of_core", "decode_box", "decode_box_mean", "decode_slice", "decode_slice_udtf", "effective_dimension", "factor_pivot", "first_vector_degrees", "full_expansion_size"])
def test_reads_its_table(spark, tmp_path, name):
    with pytest.raises(AnalysisException, match="PATH_NOT_FOUND"):
        QUERIES[name](spark, str(tmp_path)).collect()


@pytest.fixture(scope="module")
def twice(sf, tmp_path_factory):
    """Two copies of lineitem and orders: 12,000 points, a number for which no results were measured."""
    import duckdb

    folder = tmp_path_factory.mktemp("twice")
    for t, key in (("lineitem", "l_orderkey"), ("orders", "o_orderkey")):
        duckdb.sql(f"copy (select t.* replace ({key} + i * 1000000 as {key}) from '{of(sf, t)}' t, range(2) r(i)) to '{folder}/{t}.parquet'")
    return str(folder)


def solved(points, model):
    """Errors at all points before and after dense least squares on the driver, to two decimals."""
    p = points.toPandas()
    w, u = model.design([p[f"c{k + 1}"].to_numpy() for k in range(model.d)]), p["u"].to_numpy()
    errors = [np.linalg.norm(u - w @ x) / np.linalg.norm(u) for x in (model.core.ravel(), np.linalg.lstsq(w, u)[0])]
    return len(p), "x".join(map(str, model.ranks)), *(float(np.floor(e * 100 + 0.5) / 100) for e in errors)


def test_three_axes_return_the_numbers_of_any_size(spark, twice):
    got = [tuple(r) for r in QUERIES["compress_front3"](spark, twice).collect()]
    for rate, row in zip((0.1, 1.0), got, strict=True):
        n, ranks, before, after = solved(base.line(spark, twice), base.model3(spark, twice, rate=rate))
        assert n == 12000 and row == (n, rate, ranks, before, after)


def test_four_axes_return_the_numbers_of_any_size(spark, twice):
    got = [tuple(r) for r in QUERIES["compress_front4"](spark, twice).collect()]
    want = solved(tables.order_points(spark, twice), base.model4(spark, twice))
    assert want[0] == 12000 and got == [want]


def test_both_cases_return_the_numbers_of_any_size(spark, twice):
    got = [tuple(r) for r in QUERIES["compression_table"](spark, twice).collect()]
    cases = (("three axes", base.line(spark, twice), base.model3(spark, twice)), ("four axes", tables.order_points(spark, twice), base.model4(spark, twice)))
    want = [(name, n, 8 * n, ranks, model.R, after) for name, points, model in cases for n, ranks, _, after in [solved(points, model)]]
    assert want[0][1] == 12000 and got == want
