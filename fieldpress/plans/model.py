"""The functional Tucker model: a core and sparse functions of one variable for each axis.

It is small (kilobytes to a few megabytes), so it travels inside closures; a bundle is
four small Parquet tables.
"""

from __future__ import annotations

import json
from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from ..functions import basis as B
from ..schema import AXES, CORE, FORMAT_VERSION, META, MODE_FUNCTIONS, AxisSpec, BasisSpec


@dataclass
class ModeFunction:
    """One function of one axis: coefficients on a basis of the unit interval."""

    basis: BasisSpec
    coef: dict[int, float]
    fit_err: float = 0.0
    loo_err: float = 0.0

    def __call__(self, x: np.ndarray) -> np.ndarray:
        return B.evaluate_matrix(x, self.basis) @ self.dense()

    def dense(self) -> np.ndarray:
        out = np.zeros(self.basis.size)
        out[list(self.coef)] = list(self.coef.values())
        return out


@dataclass
class Meta:
    eps_requested: float = 0.0
    regrid_fraction: float = 1.0
    err_tensor: float = 0.0
    err_fit: float = 0.0
    err_points: float = 0.0
    n_points: int = 0
    seed: int = 0
    options: dict = field(default_factory=dict)


@dataclass
class FunctionalTucker:
    axes: list[AxisSpec]
    core: np.ndarray
    functions: list[list[ModeFunction]]
    meta: Meta = field(default_factory=Meta)

    @property
    def d(self) -> int:
        return len(self.axes)

    @property
    def ranks(self) -> tuple[int, ...]:
        return self.core.shape

    @property
    def R(self) -> int:
        return int(self.core.size)

    @property
    def nnz(self) -> int:
        return sum(len(f.coef) for fs in self.functions for f in fs)

    def unit(self, k: int, c: np.ndarray) -> np.ndarray:
        a = self.axes[k]
        return np.clip((np.asarray(c, float) - a.lo) / (a.hi - a.lo), 0, 1) if a.hi > a.lo else np.zeros(len(c))

    def mode_values(self, k: int, c: np.ndarray) -> np.ndarray:
        """len(c) by r_k values of axis k's functions. Functions of one basis share its evaluation; repeated coordinates are evaluated once."""
        out, back = self.mode_kinds(k, c)
        return out[back]

    def mode_kinds(self, k: int, c: np.ndarray, many: bool = False) -> tuple[np.ndarray, np.ndarray]:
        """The values at the distinct coordinates only, and each coordinate's place among them. ``many``: by the quicker sums for many coordinates (another rounding)."""
        x = self.unit(k, c)
        kinds, back = np.unique(x, return_inverse=True)
        out = np.empty((len(kinds), len(self.functions[k])))
        for spec in {f.basis for f in self.functions[k]}:
            at = [j for j, f in enumerate(self.functions[k]) if f.basis == spec]
            coef = np.stack([self.functions[k][j].dense() for j in at], axis=1)
            out[:, at] = B.combine(kinds, spec, coef) if many else B.evaluate_matrix(kinds, spec) @ coef
        return out, back

    def design(self, cols: list[np.ndarray]) -> np.ndarray:
        """Rows of products of mode functions, ordered as the core (last mode fastest)."""
        out = np.ones((len(cols[0]), 1))
        for k, c in enumerate(cols):
            out = (out[:, :, None] * self.mode_values(k, c)[:, None, :]).reshape(len(c), -1)
        return out

    def evaluate(self, cols: list[np.ndarray]) -> np.ndarray:
        """Values at points: modes are contracted one after the other, the largest rank first."""
        order = sorted(range(self.d), key=lambda k: -self.ranks[k])
        n = len(cols[0])
        if n == 0:
            return np.zeros(0)
        x = np.transpose(self.core, order)
        first = self.mode_values(order[0], cols[order[0]])
        x = (first @ x.reshape(x.shape[0], -1)).reshape(n, *x.shape[1:])
        for k in order[1:]:
            x = np.einsum("nj...,nj->n...", x, self.mode_values(k, cols[k]))
        return x

    def with_core(self, core: np.ndarray, **meta) -> "FunctionalTucker":
        return replace(self, core=np.asarray(core, float).reshape(self.core.shape), meta=replace(self.meta, **meta))

    # -- tables ------------------------------------------------------------------------

    def tables(self, spark: SparkSession) -> dict[str, DataFrame]:
        functions = [(k + 1, j + 1, f.basis.row(), {int(i): float(c) for i, c in f.coef.items()}, len(f.coef), float(f.fit_err), float(f.loo_err)) for k, fs in enumerate(self.functions) for j, f in enumerate(fs)]
        core = [([int(i) + 1 for i in j], float(v)) for j, v in np.ndenumerate(self.core)]
        m = self.meta
        meta = [(FORMAT_VERSION, m.eps_requested, m.regrid_fraction, m.err_tensor, m.err_fit, m.err_points, m.n_points, m.seed, json.dumps(m.options, sort_keys=True))]
        axes = [(k + 1, a.name, a.lo, a.hi, a.nodes, a.kind) for k, a in enumerate(self.axes)]
        return {"axes": spark.createDataFrame(axes, AXES), "mode_functions": spark.createDataFrame(functions, MODE_FUNCTIONS), "core": spark.createDataFrame(core, CORE), "meta": spark.createDataFrame(meta, META)}

    def save(self, spark: SparkSession, path: str) -> None:
        for name, df in self.tables(spark).items():
            df.coalesce(1).write.mode("overwrite").parquet(f"{path}/{name}")

    def to_json(self) -> str:
        functions = [[{"basis": f.basis.row(), "coef": {str(i): c for i, c in f.coef.items()}, "errors": [f.fit_err, f.loo_err]} for f in fs] for fs in self.functions]
        return json.dumps({"axes": [[a.name, a.lo, a.hi, a.nodes, a.kind] for a in self.axes], "ranks": list(self.ranks), "core": self.core.ravel().tolist(), "functions": functions})

    @staticmethod
    def from_json(text: str) -> "FunctionalTucker":
        x = json.loads(text)
        functions = [[ModeFunction(BasisSpec(f["basis"]["family"], f["basis"]["degree"], f["basis"]["resolution"]), {int(i): c for i, c in f["coef"].items()}, *f["errors"]) for f in fs] for fs in x["functions"]]
        return FunctionalTucker([AxisSpec(*a) for a in x["axes"]], np.array(x["core"]).reshape(x["ranks"]), functions)

    @staticmethod
    def load(spark: SparkSession, path: str) -> "FunctionalTucker":
        read = {n: spark.read.parquet(f"{path}/{n}").collect() for n in ("axes", "mode_functions", "core", "meta")}
        return FunctionalTucker.from_rows(**read)

    @staticmethod
    def from_rows(axes, mode_functions, core, meta) -> "FunctionalTucker":
        m = meta[0]
        if m["format_version"] != FORMAT_VERSION:
            raise ValueError(f"format version {m['format_version']} is not {FORMAT_VERSION}")
        ax = [AxisSpec(r["name"], r["lo"], r["hi"], r["nodes"], r["kind"]) for r in sorted(axes, key=lambda r: r["k"])]
        fs: list[list[ModeFunction]] = [[] for _ in ax]
        for r in sorted(mode_functions, key=lambda r: (r["k"], r["j"])):
            b = r["basis"]
            fs[r["k"] - 1].append(ModeFunction(BasisSpec(b["family"], b["degree"], b["resolution"]), dict(r["coef"]), r["fit_err"], r["loo_err"]))
        out = np.zeros([len(f) for f in fs])
        for r in core:
            out[tuple(i - 1 for i in r["j"])] = r["v"]
        return FunctionalTucker(ax, out, fs, Meta(m["eps_requested"], m["regrid_fraction"], m["err_tensor"], m["err_fit"], m["err_points"], m["n_points"], m["seed"], json.loads(m["options"])))


def rank_one(axes: list[AxisSpec], functions: list[ModeFunction], weight: float = 1.0) -> FunctionalTucker:
    """A product of one function an axis."""
    return FunctionalTucker(axes, np.full([1] * len(axes), weight), [[f] for f in functions])


def canonical_terms(model: FunctionalTucker, top: int | None = None) -> FunctionalTucker:
    """The model with only the ``top`` core entries of largest size (all others 0): a sum of so many rank-one terms."""
    flat = model.core.ravel()
    keep = np.lexsort((np.arange(flat.size), -np.abs(flat)))[: top or flat.size]
    core = np.zeros(flat.size)
    core[keep] = flat[keep]
    return model.with_core(core)
