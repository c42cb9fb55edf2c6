"""Cases that the third review found: work that grew faster than its points."""

import numpy as np

from fieldpress.operators import lstsq, regrid, sampling
from fieldpress.operators.axes import unit_axes
from fieldpress.plans.model import FunctionalTucker, ModeFunction
from fieldpress.registry import base, reports
from fieldpress.schema import indices, legendre
from tests.test_registry import QUERIES


def dependent(ranks, degree):
    """Axes with more functions than their space has dimensions."""
    rng = np.random.default_rng(3)
    make = lambda: ModeFunction(legendre(degree), dict(enumerate(rng.normal(size=degree + 1).tolist())))
    return FunctionalTucker(unit_axes([r + 2 for r in ranks]), np.zeros(ranks), [[make() for _ in range(r)] for r in ranks])


def test_dependent_functions_do_not_hinder_the_rounds(spark, sf):
    points, m = base.line(spark, sf).persist(), dependent((7, 6, 6), 3)
    p = points.toPandas()
    w, u = m.design([p[c].to_numpy() for c in ("c1", "c2", "c3")]), p["u"].to_numpy()
    want = np.linalg.norm(u - w @ np.linalg.lstsq(w, u)[0])
    got = lstsq.lsqr(points, m)
    assert got.converged and got.rounds < 100 and got.core.shape == (m.R,)
    assert np.isclose(np.linalg.norm(u - w @ got.core), want, rtol=1e-9)
    assert np.isclose(np.sqrt(got.residual2), want, rtol=1e-6)
    points.unpersist()


def test_coordinates_that_recur_on_the_leading_axis():
    rng, m = np.random.default_rng(4), dependent((5, 4, 3), 5)
    cols = [rng.integers(0, 30, 4000) / 32, rng.random(4000), rng.integers(0, 5, 4000) / 8]
    y, core, w = rng.normal(size=4000), rng.normal(size=m.ranks), m.design(cols)
    shared = lstsq.SharedRows(m, cols)
    assert (shared.run, shared.lead) == (2, 0) and shared._starts(slice(0, 800)) is not None
    assert np.allclose(shared.transposed(y).ravel(), w.T @ y) and np.allclose(shared.values(core), w @ core.ravel())
    assert np.allclose(shared.squared().transposed(y).ravel(), (w * w).T @ y)
    assert np.allclose(lstsq.unpaired(shared.transposed(np.ones(4000), pairs=True), m.ranks), w.T @ w)


def test_a_grid_that_a_task_holds_is_summed_without_rows_to_aggregate(spark, sf):
    points, axes = base.line(spark, sf), unit_axes([9, 8, 5])
    got = regrid.fused_moments(points, axes)
    assert "Aggregate" not in got._jdf.queryExecution().toString()
    a, b = ({tuple(r[i] for i in indices(3)): r for r in x.collect()} for x in (got, regrid.node_moments(points, axes)))
    assert a.keys() == b.keys()
    assert all(np.allclose([a[i][c] for c in got.columns], [b[i][c] for c in got.columns], rtol=1e-9, atol=1e-9) for i in a)


def test_keys_are_hashed_once_for_all_variables(spark, sf, monkeypatch):
    drawn, one, together = [], sampling.hash_fraction, reports.together
    monkeypatch.setattr(sampling, "hash_fraction", lambda points, rate, *a: (rate < 1 and drawn.append(rate)) or one(points, rate, *a))
    monkeypatch.setattr(reports, "together", lambda s, f, names: together(s, f, ["constant", "affine"]))
    assert {r.name for r in QUERIES["eleven_report"](spark, sf).collect()} == {"constant", "affine"}
    assert drawn == [base.RATE]
