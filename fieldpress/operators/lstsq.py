"""Least squares for the core: full (Gram sums or a tree of QR factors), iterative for cores of any size, and small dense solves.

Tasks are as many as the cores, however many splits the input has: each reduces its rows
to one block. Blocks that add up are cut into panels and every panel is summed by one task
of a single shuffle; QR factors are merged in levels of ``FAN`` blocks. Only the finished
block reaches the driver, panel by panel. Where R x R numbers are too many for a driver,
``lsqr`` needs vectors of R numbers only.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from copy import copy
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import RDD, StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.model import FunctionalTucker
from ..schema import coords
from .design import SLICE, columns, held, slices
from .storage import cut, discard

#: Largest R for which R x R blocks are solved on the driver; beyond it cores are found by ``lsqr``.
MAX_R = 5000
#: Numbers in a panel of a block.
PANEL = 1_000_000
#: Blocks of a level that one task merges.
FAN = 4
#: Bytes of the tasks' sums that a round of ``lsqr`` may send to the driver.
DIRECT = 64_000_000
#: Smallest R whose Gram matrix is summed by products of pairs of functions.
PAIRED_R = 256


@dataclass
class Solution:
    core: np.ndarray
    residual2: float
    total2: float
    condition: float
    rows: int
    underdetermined: bool = False
    rounds: int = 0
    converged: bool = True

    @property
    def relative_residual(self) -> float:
        return float(np.sqrt(max(self.residual2, 0.0) / self.total2)) if self.total2 > 0 else 0.0


def _tasks(rows: DataFrame) -> DataFrame:
    """rows in at most as many partitions as the cluster has cores (no shuffle): a block a core, not a block a split."""
    return rows.coalesce(max(1, rows.sparkSession.sparkContext.defaultParallelism))


Maker = Callable[[Iterator[pa.RecordBatch]], np.ndarray | None]


def panels(rows: DataFrame, make: Maker) -> DataFrame:
    """panel, block: make() turns a task's batches into one array (None: nothing); its panels."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = make(batches)
        if block is not None:
            flat = np.ascontiguousarray(block, float).ravel()
            for i in range(0, flat.size, PANEL):
                yield pa.RecordBatch.from_arrays([pa.array([i // PANEL], pa.int64()), pa.array([flat[i : i + PANEL].tobytes()], pa.binary())], names=["panel", "block"])

    return _tasks(rows).mapInArrow(run, "panel long, block binary")


def sum_blocks(rows: DataFrame, make: Maker, shape: tuple[int, ...]) -> np.ndarray | None:
    """The sum of all tasks' arrays (of this shape), or None without any. One shuffle by panel; a task holds one sum a panel."""

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, np.ndarray] = {}
        for batch in batches:
            for k, x in zip(batch.column("panel").to_pylist(), batch.column("block")):
                part = np.frombuffer(x.as_buffer())
                if k in total:
                    total[k] += part
                else:
                    total[k] = part.copy()
        for k, x in total.items():
            yield pa.RecordBatch.from_arrays([pa.array([k], pa.int64()), pa.array([x.tobytes()], pa.binary())], names=["panel", "block"])

    count = -(-int(np.prod(shape)) // PANEL)
    few = max(1, min(count, rows.sparkSession.sparkContext.defaultParallelism))
    out = None
    for r in panels(rows, make).repartition(few, "panel").mapInArrow(add, "panel long, block binary").toLocalIterator():
        out = np.zeros(int(np.prod(shape))) if out is None else out
        at = r["panel"] * PANEL
        part = np.frombuffer(r["block"])
        out[at : at + len(part)] = part
    return None if out is None else out.reshape(shape)


def merge_blocks(rows: DataFrame, make: Maker, join: Callable[[np.ndarray, np.ndarray], np.ndarray], width: int) -> np.ndarray | None:
    """One block (any rows x width) from all tasks', joined in levels of ``FAN`` until one is left."""
    schema = "part long, block binary"

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        block = make(batches)
        if block is not None:
            yield pa.RecordBatch.from_arrays([pa.array([TaskContext.get().partitionId()], pa.int64()), pa.array([block.tobytes()], pa.binary())], names=["part", "block"])

    def level(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, np.ndarray] = {}
        for batch in batches:
            for k, x in zip(batch.column("part").to_pylist(), batch.column("block")):
                part = np.frombuffer(x.as_buffer()).reshape(-1, width)
                total[k // FAN] = join(total[k // FAN], part) if k // FAN in total else part
        for k, x in total.items():
            yield pa.RecordBatch.from_arrays([pa.array([k], pa.int64()), pa.array([np.ascontiguousarray(x).tobytes()], pa.binary())], names=["part", "block"])

    src = _tasks(rows)
    left = max(1, rows.sparkSession.sparkContext.defaultParallelism)
    blocks = src.mapInArrow(first, schema)
    while left > 1:
        left = -(-left // FAN)
        blocks = blocks.repartition(left, F.floor(F.col("part") / FAN)).mapInArrow(level, schema)
    total = None
    for r in blocks.toLocalIterator():  # one block, or few where an input has more partitions than cores
        x = np.frombuffer(r["block"]).reshape(-1, width)
        total = x if total is None else join(total, x)
    return total


class SharedRows:
    """Design rows of some points without the rows. The points lie in runs of equal coordinate on the axis with the fewest distinct ones (one run of all, if these are too many to pay): that axis enters once a run, not once a point. Within a run they are sorted on the axis that leads the matrix products, which takes coordinates that recur there once. ``turns``: matrices that turn each axis's functions into others."""

    def __init__(self, model: FunctionalTucker, cols: list[np.ndarray], turns: list[np.ndarray] | None = None):
        n = len(cols[0])
        kinds, back = zip(*[model.mode_kinds(k, c, many=True) for k, c in enumerate(cols)])
        few = int(np.argmin([len(x) for x in kinds]))
        self.kinds, self.run = [x if turns is None else x @ turns[k] for k, x in enumerate(kinds)], few if n >= 16 * len(kinds[few]) else None
        free = [k for k in range(len(kinds)) if k != self.run]
        self.lead = min((k for k in free if 4 * len(kinds[k]) <= n), key=lambda k: len(kinds[k]), default=max(free, key=lambda k: self.kinds[k].shape[1], default=None))
        keys = [back[k] for k in (self.lead, self.run) if k is not None]
        self.order = np.lexsort(keys) if keys else np.arange(n)
        self.back = [b[self.order] for b in back]
        self.edges = np.array([0, n]) if self.run is None else np.searchsorted(self.back[few], np.arange(len(kinds[few]) + 1))

    def squared(self) -> "SharedRows":
        """The rows of squares."""
        out = copy(self)
        out.kinds = [x * x for x in self.kinds]
        return out

    def _plan(self, sizes: list[int]) -> tuple[int | None, list[int], int]:
        """The axis that leads the matrix products, the others in order, numbers a run."""
        free = [k for k in range(len(sizes)) if k != self.run]
        return self.lead, [k for k in free if k != self.lead], int(np.prod([sizes[k] for k in free]))

    def _starts(self, at: slice) -> np.ndarray | None:
        """Where the leading axis's coordinate changes; None where it seldom recurs."""
        b = self.back[self.lead][at]
        starts = np.flatnonzero(np.concatenate([[True], b[1:] != b[:-1]]))
        return starts if 2 * len(starts) <= len(b) else None

    def _values(self, k: int, at: slice, pairs: bool) -> np.ndarray:
        return _pairs(self.kinds[k][self.back[k][at]], pairs)

    def transposed(self, y: np.ndarray, pairs: bool = False) -> np.ndarray:
        """The sum over points of y times the product of the axes' functions; ``pairs``: of the axes' products of two functions."""
        y = y[self.order]
        sizes = [_pair_count(x.shape[1]) if pairs else x.shape[1] for x in self.kinds]
        lead, rest, width = self._plan(sizes)
        step = max(1, SLICE // max(width // (sizes[lead] if lead is not None else 1), sizes[lead] if lead is not None else 1))
        runs, many = len(self.edges) - 1, max(1, SLICE // width)
        first = 1 if self.run is None else sizes[self.run]
        out = np.zeros((first, width))
        for low in range(0, runs, many):
            top = min(runs, low + many)
            sums = np.zeros((top - low, width))
            for j in range(low, top):
                for i in range(self.edges[j], self.edges[j + 1], step):
                    at = slice(i, min(i + step, self.edges[j + 1]))
                    w = y[at, None]
                    for k in rest:
                        w = (w[:, :, None] * self._values(k, at, pairs)[:, None, :]).reshape(len(w), -1)
                    if lead is None:
                        sums[j - low] += w.sum(axis=0)
                        continue
                    starts = self._starts(at)
                    if starts is None:
                        sums[j - low] += (self._values(lead, at, pairs).T @ w).ravel()
                    else:
                        once = _pairs(self.kinds[lead][self.back[lead][at][starts]], pairs)
                        sums[j - low] += (once.T @ np.add.reduceat(w, starts, axis=0)).ravel()
            out += sums if self.run is None else _pairs(self.kinds[self.run][low:top], pairs).T @ sums
        axes = [*([] if self.run is None else [self.run]), *([] if lead is None else [lead]), *rest]
        return np.transpose(out.reshape([sizes[k] for k in axes]), np.argsort(axes))

    def values(self, core: np.ndarray) -> np.ndarray:
        """The model with this core at the points, in their order."""
        sizes = list(core.shape)
        lead, rest, width = self._plan(sizes)
        core = np.transpose(core, [*([] if self.run is None else [self.run]), *([] if lead is None else [lead]), *rest])
        flat = core.reshape(-1, width)
        step = max(1, SLICE // max(width // (sizes[lead] if lead is not None else 1), sizes[lead] if lead is not None else 1))
        runs, many = len(self.edges) - 1, max(1, SLICE // width)
        out = np.empty(len(self.order))
        for low in range(0, runs, many):
            top = min(runs, low + many)
            now = flat if self.run is None else self.kinds[self.run][low:top] @ flat
            for j in range(low, top):
                for i in range(self.edges[j], self.edges[j + 1], step):
                    at = slice(i, min(i + step, self.edges[j + 1]))
                    starts = None if lead is None else self._starts(at)
                    if lead is None:
                        x = np.full((at.stop - i, 1), now[j - low, 0])
                    elif starts is None:
                        x = self._values(lead, at, False) @ now[j - low].reshape(sizes[lead], -1)
                    else:
                        once = self.kinds[lead][self.back[lead][at][starts]] @ now[j - low].reshape(sizes[lead], -1)
                        x = np.repeat(once, np.diff(np.append(starts, at.stop - i)), axis=0)
                    for k in rest:
                        x = np.einsum("ni,nij->nj", self._values(k, at, False), x.reshape(len(x), sizes[k], -1))
                    out[at] = x[:, 0]
        back = np.empty_like(out)
        back[self.order] = out
        return back


def _pair_count(r: int) -> int:
    return r * (r + 1) // 2


def _pairs(values: np.ndarray, pairs: bool = True) -> np.ndarray:
    if not pairs:
        return values
    a, b = np.triu_indices(values.shape[1])
    return values[:, a] * values[:, b]


def unpaired(sums: np.ndarray, ranks: tuple[int, ...]) -> np.ndarray:
    """The R x R Gram matrix from its distinct numbers: sums over points of the axes' products of two functions."""
    d, at = len(ranks), []
    for k, r in enumerate(ranks):
        place = np.zeros((r, r), int)
        a, b = np.triu_indices(r)
        place[a, b] = place[b, a] = np.arange(len(a))
        at.append(place.reshape([r if j in (k, d + k) else 1 for j in range(2 * d)]))
    n = int(np.prod(ranks))
    return sums[tuple(at)].reshape(n, n)


def paired_moments(points: DataFrame, model: FunctionalTucker) -> tuple[np.ndarray, np.ndarray, float, int]:
    """``moments`` for a core of many entries. The products of two design rows' entries are products of pairs of the axes' functions, so a Gram matrix of R x R numbers holds only prod r_k (r_k + 1) / 2 different ones; these are summed, one axis a run of equal coordinates at a time."""
    d, r = model.d, model.R
    shape = [_pair_count(x) for x in model.ranks]
    size = int(np.prod(shape))

    def make(batches):
        total = np.zeros(size + r + 2)
        for *cols, u in held(batches, [*coords(d), "u"]):
            rows = SharedRows(model, cols)
            total[:size] += rows.transposed(np.ones(len(u)), pairs=True).ravel()
            total[size : size + r] += rows.transposed(u).ravel()
            total[size + r :] += u @ u, len(u)
        return total

    got = sum_blocks(points.select(*coords(d), "u"), make, (size + r + 2,))
    got = np.zeros(size + r + 2) if got is None else got
    return unpaired(got[:size].reshape(shape), model.ranks), got[size : size + r], float(got[-2]), int(got[-1])


def moments(points: DataFrame, model: FunctionalTucker) -> tuple[np.ndarray, np.ndarray, float, int]:
    """Gram matrix, right side, sum of squares and number of rows over all points; one scan."""
    d, r = model.d, model.R
    if r > MAX_R:
        raise ValueError(f"a core of {r} entries: use lsqr, refit_core or refit_top")
    if r >= PAIRED_R and max(model.ranks) ** 2 <= r:
        return paired_moments(points, model)

    def make(batches):
        total = np.zeros((r + 1, r + 2))
        for batch in batches:
            for part in slices(batch, r):
                w = np.concatenate([model.design(columns(part, d)), part.column("u").to_numpy(zero_copy_only=False)[:, None]], axis=1)
                total[:, : r + 1] += w.T @ w
                total[r, r + 1] += len(w)
        return total

    block = sum_blocks(points.select(*coords(d), "u"), make, (r + 1, r + 2))
    if block is None:
        block = np.zeros((r + 1, r + 2))
    return block[:r, :r], block[:r, r], float(block[r, r]), int(block[r, r + 1])


def solve_gram(g: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, float]:
    """Minimum-norm solution of the normal equations and the condition number of the rows."""
    w, v = np.linalg.eigh(g)
    top = max(w[-1], 0.0) if len(w) else 0.0
    keep = w > top * 1e-14 * max(1, len(w))
    x = v[:, keep] @ ((v[:, keep].T @ b) / w[keep])
    return x, float(np.sqrt(top / w[keep][0])) if keep.any() else 1.0


def full(points: DataFrame, model: FunctionalTucker, method: str = "gram", max_r: int | None = None) -> Solution:
    """All points. gram: sums, residual without another scan; tsqr: triangular factors, for ill-conditioned rows. A core of over ``MAX_R`` entries is found by ``lsqr``."""
    if model.R > (MAX_R if max_r is None else max_r):
        return lsqr(points, model)
    if method == "gram":
        g, b, uu, n = moments(points, model)
        x, cond = solve_gram(g, b)
        return Solution(x, max(uu - float(b @ x), 0.0), uu, cond, n, n < model.R)
    if method != "tsqr":
        raise ValueError(f"unknown method {method!r}")
    d, r = model.d, model.R

    def qr(x):
        return np.linalg.qr(x, mode="r")

    def make(batches):
        total, seen = np.zeros((0, r + 2)), 0
        for batch in batches:
            for part in slices(batch, r):
                w = np.concatenate([model.design(columns(part, d)), part.column("u").to_numpy(zero_copy_only=False)[:, None]], axis=1)
                seen += len(w)
                total = np.pad(qr(np.concatenate([total[:, : r + 1], w])), ((0, 0), (0, 1)))
        if not seen:
            return None
        total[0, r + 1] = seen
        return total

    def join(a, b):
        out = np.pad(qr(np.concatenate([a[:, : r + 1], b[:, : r + 1]])), ((0, 0), (0, 1)))
        out[0, r + 1] = a[:, r + 1].sum() + b[:, r + 1].sum()
        return out

    block = merge_blocks(points.select(*coords(d), "u"), make, join, r + 2)
    if block is None:
        return Solution(np.zeros(r), 0.0, 0.0, 1.0, 0, True)
    n = int(block[:, r + 1].sum())
    a, b = block[:, :r], block[:, r]
    x = solve_small(a, b)
    s = np.linalg.svd(a, compute_uv=False)
    res = b - a @ x
    return Solution(x, float(res @ res), float(b @ b), float(s[0] / s[-1]) if s[-1] > 0 else float("inf"), n, n < r)


def solve_small(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Least squares of a matrix that fits the driver, by QR; of minimum norm if rows are short or columns (nearly) dependent."""
    if a.shape[0] >= a.shape[1] > 0:
        q, r = np.linalg.qr(a)
        d = np.abs(np.diag(r))
        if d.min() > 1e-9 * d.max():
            return np.linalg.solve(r, q.T @ b)
    return np.linalg.lstsq(a, b, rcond=None)[0]


def axis_grams(points: DataFrame, model: FunctionalTucker) -> list[np.ndarray]:
    """Mean Gram matrix of each axis's functions at the points: r_k x r_k numbers an axis, one scan."""
    sizes = [r * r for r in model.ranks]

    def make(batches):
        out = np.zeros(sum(sizes) + 1)
        for batch in batches:
            parts = [(w := model.mode_values(k, c)).T @ w for k, c in enumerate(columns(batch, model.d))]
            out += np.concatenate([*[p.ravel() for p in parts], [float(batch.num_rows)]])
        return out

    got = sum_blocks(points.select(*coords(model.d)), make, (sum(sizes) + 1,))
    got = np.zeros(sum(sizes) + 1) if got is None else got / max(got[-1], 1.0)
    cuts = np.split(got[:-1], np.cumsum(sizes)[:-1])
    return [c.reshape(r, r) for c, r in zip(cuts, model.ranks)]


class Kronecker:
    """x -> (product over axes of inverse square roots of their Gram matrices) x: the rows' columns become nearly orthonormal where the axes are nearly independent. Symmetric. Only r_k x r_k matrices."""

    def __init__(self, grams: list[np.ndarray]):
        self.roots = []
        for g in grams:
            w, v = np.linalg.eigh(g)
            keep = np.maximum(w, max(w[-1], 1e-300) * 1e-10)
            self.roots.append((v / np.sqrt(keep)) @ v.T)

    def __call__(self, x: np.ndarray) -> np.ndarray:
        t = x.reshape([len(r) for r in self.roots])
        for k, r in enumerate(self.roots):
            t = np.moveaxis(np.tensordot(r, np.moveaxis(t, k, 0), axes=1), 0, k)
        return t.ravel()


def axis_bases(places: DataFrame, model: FunctionalTucker) -> list[np.ndarray]:
    """For each axis a matrix that turns its functions into orthonormal ones at the points (column ``n``: how often), one scan. Functions that depend on others there drop out, as in ``solve_gram``: left in, their rounding errors would grow to the size of the sums. The others are turned once more, so that each lives near one coordinate, and products of them near one place."""
    sizes = [r * r for r in model.ranks for _ in range(2)]

    def make(batches):
        out = np.zeros(sum(sizes))
        for *cols, n in held(batches, [*coords(model.d), "n"]):
            at = 0
            for k, c in enumerate(cols):
                values, back = model.mode_kinds(k, c, many=True)
                for y in (n, n * model.unit(k, c)):
                    part = (values * np.bincount(back, y, len(values))[:, None]).T @ values
                    out[at : at + part.size] += part.ravel()
                    at += part.size
        return out

    got = sum_blocks(places.select(*coords(model.d), "n"), make, (sum(sizes),))
    cuts = np.split(np.zeros(sum(sizes)) if got is None else got, np.cumsum(sizes)[:-1])
    turns = []
    for k, r in enumerate(model.ranks):
        w, v = np.linalg.eigh(cuts[2 * k].reshape(r, r))
        keep = w > max(w[-1], 0.0) * 1e-14 * r
        if not keep.any():  # no point, or functions that vanish at all of them
            turns.append(np.eye(r)[:, :1])
            continue
        turn = v[:, keep] / np.sqrt(w[keep] / max(w[-1], 0.0))
        where = turn.T @ cuts[2 * k + 1].reshape(r, r) @ turn
        turns.append(turn @ np.linalg.eigh((where + where.T) / 2)[1])
    return turns


def turned(core: np.ndarray, turns: list[np.ndarray]) -> np.ndarray:
    """The core for the axes' functions from that for the turned ones."""
    for k, x in enumerate(turns):
        core = np.moveaxis(np.tensordot(x, np.moveaxis(core, k, 0), axes=1), 0, k)
    return core


Scan = Callable[[np.ndarray | None], tuple[np.ndarray, float, int]]


def conjugate(scan: Scan, r: int, precondition: Callable[[np.ndarray], np.ndarray] | None = None, tol: float = 1e-10, rounds: int = 500) -> Solution:
    """Conjugate gradients on the normal equations. scan(None): (W'u, u'u, rows); scan(x): W'Wx first. ``converged`` tells whether the residual of the (preconditioned) equations fell to tol before the rounds were used up."""
    pre = precondition or (lambda v: v)
    b, uu, n = scan(None)
    rhs = pre(b)
    z, res = np.zeros(r), rhs.copy()
    p, rr = res.copy(), float(res @ res)
    goal, done = tol * max(float(np.linalg.norm(rhs)), 1e-300), 0
    while np.sqrt(rr) > goal and done < rounds:
        ap = pre(scan(pre(p))[0])
        size = float(p @ ap)
        if size <= 0:  # the rest of the residual lies where the rows have no weight
            break
        step = rr / size
        z, res = z + step * p, res - step * ap
        new = float(res @ res)
        p, rr, done = res + new / rr * p, new, done + 1
    x = pre(z)
    # u'u - 2 b'x + x'W'Wx with W'Wx from the residual: pre(W'Wx) = rhs - res
    residual2 = uu - 2 * float(b @ x) + float(z @ (rhs - res))
    return Solution(x, max(residual2, 0.0), uu, float("nan"), n, n < r, done, bool(np.sqrt(rr) <= goal))


def packed(rows: DataFrame, names: list[str]) -> RDD:
    """The columns' numbers, ``HELD_POINTS`` rows a block of bytes, in at most as many partitions as cores. The plan is made once, however often the blocks are read."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for cols in held(batches, names):
            yield pa.RecordBatch.from_arrays([pa.array([np.stack(cols).tobytes()], pa.binary())], names=["block"])

    return _tasks(rows.select(*names)).mapInArrow(run, "block binary").rdd.map(lambda row: bytes(row.block))


def sum_parts(parts: RDD, size: int) -> np.ndarray:
    """The sum of the partitions' arrays, one each of so many numbers: added on the driver up to ``DIRECT`` bytes of them, else in a tree of tasks."""
    count = parts.getNumPartitions()
    if not count:
        return np.zeros(size)
    if count * size * 8 > DIRECT:
        return parts.treeReduce(np.add)
    return np.sum(parts.collect(), axis=0)


#: One of so many coordinates, by their hash, tells ``repeats`` how often coordinates recur.
REPEAT_SHARE = 64
#: Bytes of axis functions' values at the points that are kept between the rounds of ``lsqr``; more are made again in every round.
READY = 1_000_000_000


def repeats(points: DataFrame, d: int) -> tuple[float, list[str]]:
    """Points for each distinct coordinates, and the axes by their number of distinct ones, among the coordinates of one hash value: all points there or none, so repeats are not missed."""
    some = points.select(*coords(d)).where(F.pmod(F.xxhash64(*coords(d)), F.lit(REPEAT_SHARE)) == 0)
    row = some.groupBy(*coords(d)).agg(F.count(F.lit(1)).alias("n")).agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("k"), *[F.approx_count_distinct(c).alias(c) for c in coords(d)]).first()
    return row.n / row.k if row.k else 1.0, sorted(coords(d), key=lambda c: row[c])


def lsqr(points: DataFrame, model: FunctionalTucker, rounds: int = 500, tol: float = 1e-8, precondition: bool = True) -> Solution:
    """All points, for a core of any size: one scan a round, vectors of R numbers only, no design rows of length R (modes are contracted one after the other). The unknowns are the core of the axes' independent functions (``axis_bases``), scaled by their sums of squares. The rounds after the first need coordinates only: they are written once, sorted by the axes of few distinct ones, and points of equal coordinates are merged into one with their number where coordinates recur."""
    d = model.d
    cores = points.sparkSession.sparkContext.defaultParallelism
    places = points.select(*coords(d), F.lit(1.0).alias("n"))
    often, axes = repeats(points, d)
    if often >= 2:
        places = places.groupBy(*coords(d)).agg(F.sum("n").alias("n"))
    kept = cut(places.repartitionByRange(cores, *axes[:2]).sortWithinPartitions(*axes[:2]), "places")
    turns = axis_bases(kept, model) if precondition else [np.eye(r) for r in model.ranks]
    shape = tuple(x.shape[1] for x in turns)
    r = int(np.prod(shape))

    def summed(rows: SharedRows, y: np.ndarray) -> np.ndarray:
        return np.concatenate([rows.transposed(y).ravel(), [y @ y, float(len(y))]])

    def start() -> np.ndarray:
        def make(batches):
            out = np.zeros(r + 2)
            for *cols, u in held(batches, [*coords(d), "u"]):
                out += summed(SharedRows(model, cols, turns), u)
            return out

        got = sum_blocks(points.select(*coords(d), "u"), make, (r + 2,))
        return np.zeros(r + 2) if got is None else got

    def ready(block: bytes) -> tuple[SharedRows, np.ndarray]:
        *cols, n = np.frombuffer(block).reshape(d + 1, -1)
        return SharedRows(model, cols, turns), n

    blocks = packed(kept, [*coords(d), "n"])
    if kept.count() * max(shape) * 8 <= READY:
        stored = made = blocks.map(ready)
    else:
        stored, made = blocks, blocks.map(ready)
    stored.persist(StorageLevel.MEMORY_AND_DISK)

    def over(f: Callable[[SharedRows, np.ndarray], np.ndarray]) -> np.ndarray:
        def make(part: Iterator[tuple[SharedRows, np.ndarray]]) -> Iterator[np.ndarray]:
            out = np.zeros(r)
            for rows, n in part:
                out += f(rows, n).ravel()
            yield out

        return sum_parts(made.mapPartitions(make), r)

    def scan(x: np.ndarray | None) -> tuple[np.ndarray, float, int]:
        if x is None:
            got = start()
            return got[:r], float(got[r]), int(got[r + 1])
        core = x.reshape(shape)
        return over(lambda rows, n: rows.transposed(rows.values(core) * n)), 0.0, 0

    scale = None
    if precondition:
        own = over(lambda rows, n: rows.squared().transposed(n))
        scale = 1 / np.sqrt(np.maximum(own, max(own.max(), 1e-300) * 1e-12))
    found = conjugate(scan, r, None if scale is None else lambda v: v * scale, tol, rounds)
    stored.unpersist()
    discard(kept)
    found.core = turned(found.core.reshape(shape), turns).ravel()
    found.underdetermined = found.rows < model.R
    return found


def lsqr_rows(rows: DataFrame, r: int, precondition: Callable[[np.ndarray], np.ndarray] | None = None, rounds: int = 500, tol: float = 1e-10) -> Solution:
    """The same over stored rows (column ``row``: R entries and the right side), which stay where they are: for sketches too large for the driver."""
    src = rows.select("row")

    def scan(x: np.ndarray | None) -> tuple[np.ndarray, float, int]:
        def make(batches):
            out = np.zeros(r + 2)
            for batch in batches:
                for part in slices(batch, r):
                    w = part.column("row").flatten().to_numpy().reshape(-1, r + 1)
                    y = w[:, r] if x is None else w[:, :r] @ x
                    out[:r] += w[:, :r].T @ y
                    out[r] += y @ y
                    out[r + 1] += len(w)
            return out

        got = sum_blocks(src, make, (r + 2,))
        got = np.zeros(r + 2) if got is None else got
        return got[:r], float(got[r]), int(got[r + 1])

    return conjugate(scan, r, precondition, tol, rounds)
