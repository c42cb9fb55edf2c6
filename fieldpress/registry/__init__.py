"""Registered queries and the SQL that says what each must return.

Each query has the signature (spark, sf_dir) -> DataFrame. SQL either recomputes the
result or states values known by construction (planted fields, exact ranks, bounds).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .base import QUERIES, SQL  # noqa: F401


def _load() -> None:
    from . import functions, points, refits, relational, reports, tensors  # noqa: F401


_load()


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Compress front3 over lineitem, re-estimate the core by the sketch, decode every point."""
    from ..operators import decode
    from ..plans.refit import refit_core
    from .base import model3, line

    points = line(spark, sf_dir)
    model = refit_core(points, model3(spark, sf_dir), oversample=4, b=256).model
    return decode.residuals(points, model).select("pt_key", "u", "u_hat", "resid")
