"""From scattered points to a structured grid.

Every point spreads to the 2^d nodes of its cell; node sums are combined map-side before
the shuffle, so that what is shuffled follows the touched nodes and not the points. Plane
fits are solved in Arrow batches, all nodes of a batch at once.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..schema import AxisSpec, coords, indices, tensor_schema
from .axes import local
from .design import held as held_points


def corners(points: DataFrame, axes: list[AxisSpec]) -> DataFrame:
    """One row for each point and node of its cell: i1..id, w (tent weight), a1..ad (offset from the node in steps), u."""
    d = len(axes)
    t = [local(F.col(c), a) for c, a in zip(coords(d), axes)]
    low = [F.least(F.floor(x), F.lit(max(a.nodes - 2, 0))).cast("int") for x, a in zip(t, axes)]
    base = points.select("u", *[x.alias(f"t{k}") for k, x in enumerate(t)], *[x.alias(f"b{k}") for k, x in enumerate(low)])
    made = []
    for e in range(2**d):
        bits = [e >> k & 1 for k in range(d)]
        if any(b and a.nodes < 2 for b, a in zip(bits, axes)):
            continue
        w: Column = F.lit(1.0)
        for k, b in enumerate(bits):
            f = F.col(f"t{k}") - F.col(f"b{k}")
            w = w * (f if b else 1.0 - f)
        made.append(F.struct(*[(F.col(f"b{k}") + b).alias(f"i{k + 1}") for k, b in enumerate(bits)], w.alias("w")))
    rows = base.select("u", *[f"t{k}" for k in range(d)], F.explode(F.array(*made)).alias("n")).select("u", *[f"t{k}" for k in range(d)], "n.*")
    return rows.where("w > 0").select(*indices(d), "w", *[(F.col(f"t{k}") - F.col(f"i{k + 1}")).alias(f"a{k + 1}") for k in range(d)], "u")


def nearest(points: DataFrame, axes: list[AxisSpec]) -> DataFrame:
    """Mean of the points nearest to each node."""
    d = len(axes)
    at = [F.floor(local(F.col(c), a) + 0.5).cast("int").alias(i) for c, a, i in zip(coords(d), axes, indices(d))]
    return points.select(*at, "u").groupBy(*indices(d)).agg(F.avg("u").alias("v"), F.count(F.lit(1)).cast("double").alias("support"))


def tent_average(points: DataFrame, axes: list[AxisSpec]) -> DataFrame:
    """Mean weighted by the product of tents over the adjacent cells."""
    d = len(axes)
    return corners(points, axes).groupBy(*indices(d)).agg((F.sum(F.col("w") * F.col("u")) / F.sum("w")).alias("v"), F.sum("w").alias("support"))


def node_moments(points: DataFrame, axes: list[AxisSpec]) -> DataFrame:
    """Weighted sums for a plane fit at each node: m_p_q (p <= q, 0 is the constant), b_p, s2 (sum of squared weights)."""
    d = len(axes)
    terms = [F.lit(1.0), *[F.col(f"a{k + 1}") for k in range(d)]]
    sums = [F.sum(F.col("w") * terms[p] * terms[q]).alias(f"m_{p}_{q}") for p in range(d + 1) for q in range(p, d + 1)]
    sums += [F.sum(F.col("w") * terms[p] * F.col("u")).alias(f"b_{p}") for p in range(d + 1)]
    return corners(points, axes).groupBy(*indices(d)).agg(*sums, F.sum(F.col("w") * F.col("w")).alias("s2"))


#: Nodes that a task holds before it passes partial sums on; a grid of no more is summed whole in every task.
HELD_NODES = 400_000
#: Nodes of such a grid whose sums are shuffled together.
BLOCK_NODES = 8_192


def fused_moments(points: DataFrame, axes: list[AxisSpec], hold: int = HELD_NODES) -> DataFrame:
    """The same sums without a row for each corner: every Arrow batch is summed by node in numpy, a task merges its batches (at most ``hold`` nodes at a time), and only those sums are shuffled: once a task, in blocks of nodes, if the grid has at most ``hold`` nodes."""
    d = len(axes)
    pairs = [(p, q) for p in range(d + 1) for q in range(p, d + 1)]
    names = [*[f"m_{p}_{q}" for p, q in pairs], *[f"b_{p}" for p in range(d + 1)], "s2"]
    nodes = [a.nodes for a in axes]

    def by_node(ids: np.ndarray, values: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        kinds, inv = np.unique(ids, return_inverse=True)
        return kinds, np.stack([np.bincount(inv, v, len(kinds)) for v in values], axis=1)

    def corner_sums(cols: list[np.ndarray], u: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
        low, off = [], []
        for k, (a, c) in enumerate(zip(axes, cols)):
            t = np.clip((c - a.lo) / (a.hi - a.lo), 0, 1) * (a.nodes - 1) if a.hi > a.lo else np.zeros(len(c))
            b = np.minimum(np.floor(t), max(a.nodes - 2, 0)).astype(np.int64)
            low.append(b)
            off.append(t - b)
        ids, ws, offs = [], [], [[] for _ in range(d)]
        for e in range(2**d):
            bits = [e >> k & 1 for k in range(d)]
            if any(b and n < 2 for b, n in zip(bits, nodes)):
                continue
            w, node = np.ones(len(u)), np.zeros(len(u), np.int64)
            for k, b in enumerate(bits):
                w = w * (off[k] if b else 1 - off[k])
                node = node * nodes[k] + low[k] + b
            ids.append(node)
            ws.append(w)
            for k, b in enumerate(bits):
                offs[k].append(off[k] - b)
        node, w = np.concatenate(ids), np.concatenate(ws)
        some = w > 0
        node, w = node[some], w[some]
        terms = [np.ones(len(w)), *[np.concatenate(o)[some] for o in offs]]
        uu = np.tile(u, len(ids))[some]
        wt = [w * t for t in terms]
        return node, [*[wt[p] * terms[q] for p, q in pairs], *[x * uu for x in wt], w * w]

    def of_batch(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
        u = batch.column("u").to_numpy(zero_copy_only=False)
        return by_node(*corner_sums([batch.column(c).to_numpy(zero_copy_only=False) for c in coords(d)], u))

    def out(node: np.ndarray, sums: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(node), *[pa.array(np.ascontiguousarray(sums[:, j])) for j in range(len(names))]], names=["node", *names])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []
        size = 0
        for batch in batches:
            if not batch.num_rows:
                continue
            held.append(of_batch(batch))
            size += len(held[-1][0])
            if size > hold:
                sums = np.concatenate([x[1] for x in held])
                held = [by_node(np.concatenate([x[0] for x in held]), list(sums.T))]
                size = len(held[0][0])
                if size > hold // 2:
                    yield out(*held[0])
                    held, size = [], 0
        if held:
            sums = np.concatenate([x[1] for x in held])
            yield out(*by_node(np.concatenate([x[0] for x in held]), list(sums.T)))

    schema = ", ".join(["node long", *[f"{n} double" for n in names]])
    count = int(np.prod(nodes))

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((len(names), count))
        for *cols, u in held_points(batches, [*coords(d), "u"]):
            node, values = corner_sums(cols, u)
            for row, v in zip(total, values):
                row += np.bincount(node, v, count)
        for i in range(0, count, BLOCK_NODES):
            part = np.ascontiguousarray(total[:, i : i + BLOCK_NODES])
            if part[0].any():
                yield pa.RecordBatch.from_arrays([pa.array([i // BLOCK_NODES], pa.int64()), pa.array([part.tobytes()], pa.binary())], names=["part", "block"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, np.ndarray] = {}
        for batch in batches:
            for i, x in zip(batch.column("part").to_pylist(), batch.column("block")):
                part = np.frombuffer(x.as_buffer()).reshape(len(names), -1)
                total[i] = total[i] + part if i in total else part.copy()
        for i, x in total.items():
            at = np.flatnonzero(x[0])
            yield out(at + i * BLOCK_NODES, x[:, at].T)

    if count <= hold:
        cores = points.sparkSession.sparkContext.defaultParallelism
        sums = points.select(*coords(d), "u").coalesce(cores).mapInArrow(blocks, "part long, block binary")
        total = sums.repartition(max(1, min(cores, -(-count // BLOCK_NODES))), "part").mapInArrow(add, schema)
    else:
        total = points.select(*coords(d), "u").mapInArrow(run, schema).groupBy("node").agg(*[F.sum(n).alias(n) for n in names])
    cols, rest = [], F.col("node")
    for k in reversed(range(d)):
        cols.append(F.pmod(rest, F.lit(nodes[k])).cast("int").alias(f"i{k + 1}"))
        rest = F.floor(rest / F.lit(nodes[k]))
    return total.select(*reversed(cols), *names)


def solve_planes(m: np.ndarray, b: np.ndarray, s2: np.ndarray, ridge: float, adaptive: bool) -> np.ndarray:
    """Node values of the weighted plane fits. The ridge acts on slopes only; it grows where the effective number of points is short of 3 (d + 1)."""
    n, p = b.shape
    trace = np.maximum(np.trace(m, axis1=1, axis2=2), 1e-300)
    count = m[:, 0, 0] ** 2 / np.maximum(s2, 1e-300)
    rho = np.full(n, ridge)
    if adaptive:
        short = np.clip(3 * p / np.maximum(count, 1e-9) - 1, 0, 10)
        rho = rho + 0.05 * short
    eye = np.eye(p)
    eye[0, 0] = 0
    full = m + (rho * trace)[:, None, None] * eye
    return np.linalg.solve(full, b[:, :, None])[:, 0, 0]


def from_moments(moments: DataFrame, d: int, ridge: float = 1e-9, adaptive: bool = True) -> DataFrame:
    """i1..id, v, support from the sums of ``node_moments``."""
    pairs = [(p, q) for p in range(d + 1) for q in range(p, d + 1)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            col = lambda n: batch.column(n).to_numpy(zero_copy_only=False)
            m = np.zeros((batch.num_rows, d + 1, d + 1))
            for p, q in pairs:
                m[:, p, q] = m[:, q, p] = col(f"m_{p}_{q}")
            b = np.stack([col(f"b_{p}") for p in range(d + 1)], axis=1)
            v = solve_planes(m, b, col("s2"), ridge, adaptive)
            yield pa.RecordBatch.from_arrays([*[batch.column(i) for i in indices(d)], pa.array(v), batch.column("m_0_0")], names=[*indices(d), "v", "support"])

    return moments.mapInArrow(run, tensor_schema(d).add("support", "double"))


def local_linear(points: DataFrame, axes: list[AxisSpec], ridge: float = 1e-9, adaptive: bool = True, kernel: str = "fused") -> DataFrame:
    """Weighted plane fit at every touched node; exact on affine fields where points are enough. kernel: fused, or columns (a row for each corner, all in DataFrame functions)."""
    moments = fused_moments(points, axes) if kernel == "fused" else node_moments(points, axes)
    return from_moments(moments, len(axes), ridge, adaptive)


def identity(df: DataFrame, axes: list[AxisSpec], value: str = "v") -> DataFrame:
    """Data that already sit on the nodes (columns i1..id)."""
    return df.select(*[F.col(i).cast("int").alias(i) for i in indices(len(axes))], F.col(value).cast("double").alias("v"), F.lit(1.0).alias("support"))


REGRIDDERS = {"local_linear": local_linear, "tent_average": tent_average, "nearest": nearest}


def grid(spark: SparkSession, axes: list[AxisSpec]) -> DataFrame:
    """All nodes as i1..id, from one range by arithmetic."""
    total = int(np.prod([a.nodes for a in axes]))
    cols, rest = [], F.col("id")
    for k, a in reversed(list(enumerate(axes))):
        cols.append(F.pmod(rest, F.lit(a.nodes)).cast("int").alias(f"i{k + 1}"))
        rest = F.floor(rest / F.lit(a.nodes))
    return spark.range(total).select(*reversed(cols))


def holes(tensor: DataFrame, axes: list[AxisSpec]) -> DataFrame:
    """Nodes that the tensor lacks."""
    return grid(tensor.sparkSession, axes).join(tensor, indices(len(axes)), "left_anti")


def fill_once(tensor: DataFrame, axes: list[AxisSpec]) -> DataFrame:
    """One round: an uncovered node next to covered ones takes the mean of its axis neighbours. Adds ``filled``."""
    d = len(axes)
    idx = indices(d)
    moves = F.array(*[F.struct(F.lit(k).alias("k"), F.lit(s).alias("s")) for k in range(d) for s in (-1, 1)])
    near = tensor.select(*idx, "v", F.explode(moves).alias("m"))
    near = near.select(*[(F.col(i) + F.when(F.col("m.k") == k, F.col("m.s")).otherwise(0)).alias(i) for k, i in enumerate(idx)], "v")
    for i, a in zip(idx, axes):
        near = near.where((F.col(i) >= 0) & (F.col(i) < a.nodes))
    new = near.join(tensor.select(*idx), idx, "left_anti").groupBy(*idx).agg(F.avg("v").alias("v")).withColumn("support", F.lit(0.0)).withColumn("filled", F.lit(True))
    have = tensor if "filled" in tensor.columns else tensor.withColumn("filled", F.lit(False))
    return have.unionByName(new)


def fill_holes(tensor: DataFrame, axes: list[AxisSpec], method: str = "neighbours", rounds: int = 4) -> DataFrame:
    """The tensor with all nodes (an empty one stays empty). neighbours: up to so many rounds of ``fill_once``; what is left takes the mean of the smallest block of 2, 4, 8, ... nodes a side that holds a covered node, the whole grid at last. mean: the overall mean. Each round is written once."""
    total = int(np.prod([a.nodes for a in axes]))
    idx = indices(len(axes))
    have = tensor if "filled" in tensor.columns else tensor.withColumn("filled", F.lit(False))
    if method == "mean":
        mean = tensor.agg(F.avg("v")).first()[0] or 0.0
        new = holes(have, axes).select(*idx, F.lit(mean).alias("v"), F.lit(0.0).alias("support"), F.lit(True).alias("filled"))
        return have.unionByName(new)
    from .storage import cut, discard

    have = cut(have)
    n = have.count()
    for _ in range(rounds):
        if n >= total or n == 0:
            return have
        before, have = have, cut(fill_once(have, axes))
        discard(before)
        n = have.count()
    if n >= total:
        return have
    open_ = holes(have, axes)
    for level in range(1, max(a.nodes for a in axes).bit_length() + 1):
        block = lambda df, level=level: [F.shiftright(F.col(i), level).alias(f"b{level}_{i}") for i in idx]
        means = have.groupBy(*block(have)).agg(F.avg("v").alias(f"v{level}"))
        open_ = open_.withColumns({f"b{level}_{i}": F.shiftright(F.col(i), level) for i in idx}).join(means, [f"b{level}_{i}" for i in idx], "left")
    levels = [f"v{k}" for k in range(1, max(a.nodes for a in axes).bit_length() + 1)]
    new = open_.select(*idx, F.coalesce(*levels).alias("v"), F.lit(0.0).alias("support"), F.lit(True).alias("filled"))
    done = cut(have.unionByName(new))
    discard(have)
    return done


def coverage(tensor: DataFrame, axes: list[AxisSpec]) -> DataFrame:
    """One row: nodes, touched, min_support, median_support, hole_fraction."""
    total = float(np.prod([a.nodes for a in axes]))
    return tensor.agg(F.lit(int(total)).cast("long").alias("nodes"), F.count(F.lit(1)).alias("touched"), F.min("support").alias("min_support"), F.percentile_approx("support", 0.5, 10000).alias("median_support"), (1 - F.count(F.lit(1)) / total).alias("hole_fraction"))


def cumulative_cube(cells: DataFrame, axes: list[AxisSpec], measure: str = "v") -> DataFrame:
    """Running totals along every axis over all nodes: a smooth tensor of real data. cells: i1..id and the measure, one row a cell."""
    d = len(axes)
    idx = indices(d)
    full = grid(cells.sparkSession, axes).join(cells.groupBy(*idx).agg(F.sum(measure).alias("v")), idx, "left").withColumn("v", F.coalesce("v", F.lit(0.0)))
    for i in idx:
        w = Window.partitionBy(*[x for x in idx if x != i]).orderBy(i).rowsBetween(Window.unboundedPreceding, Window.currentRow)
        full = full.withColumn("v", F.sum("v").over(w))
    return full


def triangulate(xy: np.ndarray) -> np.ndarray:
    """Delaunay triangles (rows of three point indices) by inserting one point after the other. For small sets on the driver: a reference to compare the regridders with."""
    n = len(xy)
    mid, size = xy.mean(axis=0), 1 + 40 * np.abs(xy - xy.mean(axis=0)).max()
    far = mid + size * np.array([[-1.7, -1.0], [1.7, -1.0], [0.0, 2.0]])
    pts = np.concatenate([xy, far])
    tri = [(n, n + 1, n + 2)]

    def outside(t) -> tuple[np.ndarray, float]:
        a, b, c = pts[list(t)]
        m = 2 * np.array([b - a, c - a])
        centre = np.linalg.solve(m, [b @ b - a @ a, c @ c - a @ a])
        return centre, float(((a - centre) ** 2).sum())

    circles = {tri[0]: outside(tri[0])}
    for i in range(n):
        bad = [t for t in tri if ((pts[i] - circles[t][0]) ** 2).sum() <= circles[t][1] * (1 + 1e-12)]
        edges: dict[frozenset, int] = {}
        for t in bad:
            for e in ((t[0], t[1]), (t[1], t[2]), (t[2], t[0])):
                edges[frozenset(e)] = edges.get(frozenset(e), 0) + 1
        gone = set(bad)
        tri = [t for t in tri if t not in gone]
        for e, count in edges.items():
            if count == 1:
                u, v = sorted(e)
                d1, d2 = pts[u] - pts[i], pts[v] - pts[i]
                if abs(d1[0] * d2[1] - d1[1] * d2[0]) > 1e-14 * size * size:
                    t = (u, v, i)
                    circles[t] = outside(t)
                    tri.append(t)
    return np.array([t for t in tri if max(t) < n], int).reshape(-1, 3)


def barycentric_2d(xy: np.ndarray, u: np.ndarray, nodes: np.ndarray) -> np.ndarray:
    """Linear interpolation over the triangles; NaN outside the convex hull."""
    out = np.full(len(nodes), np.nan)
    for t in triangulate(xy):
        a, b, c = xy[t]
        m = np.array([b - a, c - a]).T
        if abs(np.linalg.det(m)) < 1e-14:
            continue
        w = np.linalg.solve(m, (nodes - a).T)
        inside = (w[0] >= -1e-9) & (w[1] >= -1e-9) & (w.sum(axis=0) <= 1 + 1e-9)
        out[inside] = ((1 - w.sum(axis=0)) * u[t[0]] + w[0] * u[t[1]] + w[1] * u[t[2]])[inside]
    return out
