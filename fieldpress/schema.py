"""Specifications and table schemas of the engine."""

from __future__ import annotations

from dataclasses import asdict, dataclass, field

from pyspark.sql import types as T

FORMAT_VERSION = 1


@dataclass(frozen=True)
class AxisSpec:
    """One coordinate direction: bounds, number of equispaced nodes, and whether it is space or time."""

    name: str
    lo: float
    hi: float
    nodes: int
    kind: str = "space"

    @property
    def step(self) -> float:
        return (self.hi - self.lo) / (self.nodes - 1) if self.nodes > 1 and self.hi > self.lo else 0.0

    def node(self, i: int) -> float:
        return self.lo + i * self.step


@dataclass(frozen=True)
class BasisSpec:
    """A univariate approximation space on the unit interval.

    legendre: polynomials up to ``degree``. multiwavelet: piecewise polynomials up to
    ``degree`` on 2^resolution dyadic cells in a multiscale orthonormal basis (with
    ``levels_inclusive``, one level more). piecewise: the same space, cell by cell.
    """

    family: str
    degree: int
    resolution: int = 0
    levels_inclusive: bool = False

    @property
    def levels(self) -> int:
        return 0 if self.family == "legendre" else self.resolution + bool(self.levels_inclusive)

    @property
    def size(self) -> int:
        return (self.degree + 1) * 2**self.levels

    @property
    def tag(self) -> str:
        return f"legendre({self.degree})" if self.family == "legendre" else f"{self.family}({self.levels},{self.degree})"

    def row(self) -> dict:
        return {"family": self.family, "degree": self.degree, "resolution": self.levels}


def legendre(degree: int) -> BasisSpec:
    return BasisSpec("legendre", degree)


def multiwavelet(resolution: int, degree: int, levels_inclusive: bool = False) -> BasisSpec:
    return BasisSpec("multiwavelet", degree, resolution, levels_inclusive)


def piecewise(resolution: int, degree: int) -> BasisSpec:
    return BasisSpec("piecewise", degree, resolution)


@dataclass(frozen=True)
class FieldSpec:
    """How a table becomes points: SQL expressions of the coordinates, the value and the key columns."""

    axes: dict[str, str]
    value: str
    key: tuple[str, ...]
    kinds: dict[str, str] = field(default_factory=dict)

    @property
    def d(self) -> int:
        return len(self.axes)

    def row(self) -> dict:
        return asdict(self)


def coords(d: int) -> list[str]:
    return [f"c{k + 1}" for k in range(d)]


def indices(d: int) -> list[str]:
    return [f"i{k + 1}" for k in range(d)]


AXES = "k int, name string, lo double, hi double, nodes int, kind string"
MODE_FUNCTIONS = "k int, j int, basis struct<family:string,degree:int,resolution:int>, coef map<int,double>, nnz int, fit_err double, loo_err double"
CORE = "j array<int>, v double"
META = "format_version int, eps_requested double, regrid_fraction double, err_tensor double, err_fit double, err_points double, n_points bigint, seed int, options string"


def points_schema(d: int) -> T.StructType:
    return T.StructType([T.StructField("pt_key", T.StringType()), *[T.StructField(c, T.DoubleType()) for c in coords(d)], T.StructField("u", T.DoubleType())])


def tensor_schema(d: int) -> T.StructType:
    return T.StructType([*[T.StructField(c, T.IntegerType()) for c in indices(d)], T.StructField("v", T.DoubleType())])
