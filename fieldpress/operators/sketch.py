"""Sketches of the core regression: mixed and sampled rows, leverage scores, other projections.

Order of work: signs and blocks are columns of narrow rows (key, coordinates, value); the
one shuffle moves those; design rows are made inside the block's task, transformed, and
only the sampled outputs leave it - about S rows of R + 1 numbers in all. A sketch of up
to ``MAX_SKETCH`` bytes is solved on the driver; a larger one stays a table and is solved
by ``lstsq.lsqr_rows``.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import mixers
from ..plans.model import FunctionalTucker
from ..schema import coords
from . import mixing
from .design import SLICE, columns, slices
from .lstsq import Kronecker, Solution, axis_grams, lsqr_rows, moments, solve_small, sum_blocks
from .sampling import hash01, hash_int
from .storage import cut, discard

#: Largest sketch, in bytes, that is brought to the driver.
MAX_SKETCH = 1_000_000_000


def draw(blk: int, n: int, seed: int | str) -> np.ndarray:
    """Uniform numbers for the n outputs of a block, by MD5: a retried task, or DuckDB, draws the same."""
    return np.array([int.from_bytes(hashlib.md5(f"{blk}-{i}/{seed}".encode()).digest()[:4]) for i in range(n)]) / 4294967296.0


def _drawn(kind: str, share: float, seed: int | str, blk: int, n: int) -> tuple[np.ndarray, np.ndarray, int]:
    """(draws, outputs, length of the transform) that a block of n rows keeps."""
    size = 1 << max(0, n - 1).bit_length() if kind == "wht" else n
    h = draw(blk, size, seed)
    kept = np.flatnonzero(h < share * n / size)
    return h[kept] * (size / n), kept, size


def _transformed(model: FunctionalTucker, kind: str, cols: list[np.ndarray], u: np.ndarray, sgn: np.ndarray, size: int, kept: np.ndarray) -> np.ndarray:
    """The kept outputs of a block's signed design rows. Rows of a block too wide for memory are made and summed slice by slice."""
    n, r = len(u), model.R
    step = max(1, SLICE // (r + 1))

    def signed(i: int, j: int) -> np.ndarray:
        return np.concatenate([model.design([c[i:j] for c in cols]), u[i:j, None]], axis=1) * sgn[i:j, None]

    # a matrix product for few outputs: it is far faster an operation than the transform of all
    if kind == "none" or len(kept) <= 16 * np.log2(size + 1) or n > step:
        t = mixers.rows_of(kind, size, kept)
        return sum((t[:, i : min(i + step, n)] @ signed(i, min(i + step, n)) for i in range(0, n, step)), np.zeros((len(kept), r + 1)))
    w = signed(0, n)
    if size > n:
        w = np.concatenate([w, np.zeros((size - n, r + 1))])
    return mixers.mix(w, kind)[kept]


def _block_outputs(model: FunctionalTucker, kind: str, share: float, seed: int | str, blk: int, cols: list[np.ndarray], u: np.ndarray, sgn: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
    """(draws, outputs, rows) of a block, or None if no output is drawn."""
    h, kept, size = _drawn(kind, share, seed, blk, len(u))
    return (h, kept, _transformed(model, kind, cols, u, sgn, size, kept)) if len(kept) else None


#: Drawn blocks that are looked up in a broadcast.
MAX_DRAWN = 1_000_000


def of_drawn_blocks(rows: DataFrame, share: float, kind: str, b: int, seed: int | str, total: int) -> DataFrame:
    """rows (with blk) without the blocks of which no output is drawn, where these are most: draws need only a block's number and size, so one count by block tells, and all other rows stay out of the shuffle. The sketch is the same."""
    if share * b > 0.25 or share * total > MAX_DRAWN:
        return rows

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hit = [k for k, n in zip(batch.column("blk").to_pylist(), batch.column("n").to_pylist()) if len(_drawn(kind, share, seed, k, n)[1])]
            yield pa.RecordBatch.from_arrays([pa.array(hit, pa.int64())], names=["blk"])

    sizes = rows.groupBy("blk").agg(F.count(F.lit(1)).alias("n"))
    hit = sizes.repartition(max(1, rows.sparkSession.sparkContext.defaultParallelism)).mapInArrow(run, "blk long")
    return rows.join(F.broadcast(hit), "blk", "left_semi")


def share_of(s: int, q: int) -> float:
    """A little more than s of q, so that the s smallest draws are among them."""
    return min(1.0, (s + 5 * np.sqrt(s) + 10) / max(q, 1))


def drawn_points(points: DataFrame, d: int, s: int, kind: str = "dft", b: int = 1024, seed: int = 0, total: int | None = None) -> DataFrame:
    """The points that s mixed rows are made of, for several sketches of the same points: with the same total their sketches are those of all points."""
    q = points.count() if total is None else total
    src = mixing.blocks(points.select("pt_key", *coords(d), "u"), b, seed, q)
    return of_drawn_blocks(src, share_of(s, q), kind, b, seed, q).select("pt_key", *coords(d), "u")


def mixed_rows(points: DataFrame, model: FunctionalTucker, share: float, kind: str = "dft", b: int = 1024, scope: str = "block", seed: int = 0, total: int | None = None) -> DataFrame:
    """h, blk, out, row (R + 1 numbers): the mixed rows whose draw h is below ``share``; smaller shares are subsets.

    scope block: blocks by the hash of the key, gathered by one shuffle of narrow rows; the
    same rows for any partitioning. partition: blocks of b consecutive rows of a task, no
    shuffle; which rows meet depends on the partitioning. (global: see ``global_rows``.)
    """
    d, r = model.d, model.R
    src = mixing.signs(points.select("pt_key", *coords(d), "u"), seed)

    def record(blk: int, got) -> tuple[pa.Array, ...]:
        h, kept, out = got
        flat = pa.ListArray.from_arrays(pa.array(np.arange(len(kept) + 1) * (r + 1), pa.int32()), pa.array(out.ravel()))
        return pa.array(h), pa.array(np.full(len(kept), blk), pa.int64()), pa.array(kept, pa.int32()), flat

    if scope == "partition":

        def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            from pyspark import TaskContext

            first, held, blk = TaskContext.get().partitionId() << 32, [], 0
            size = 0

            def flush(table: pa.Table):
                got = _block_outputs(model, kind, share, seed, first + blk, [table.column(c).to_numpy() for c in coords(d)], table.column("u").to_numpy(), table.column("sgn").to_numpy())
                return None if got is None else pa.RecordBatch.from_arrays(list(record(first + blk, got)), schema=_ROWS)

            for batch in batches:
                held.append(batch)
                size += batch.num_rows
                while size >= b:
                    table = pa.Table.from_batches(held)
                    out = flush(table.slice(0, b))
                    held, size, blk = table.slice(b).to_batches(), size - b, blk + 1
                    if out is not None:
                        yield out
            if size:
                out = flush(pa.Table.from_batches(held))
                if out is not None:
                    yield out

        return src.mapInArrow(stream, "h double, blk long, out int, row array<double>")
    if scope != "block":
        raise ValueError(f"unknown scope {scope!r}")

    def run(table: pa.Table) -> pa.Table:
        t = table.sort_by([(c, "ascending") for c in ("h", "pt_key", *coords(d), "u")])
        blk = int(t.column("blk")[0].as_py())
        got = _block_outputs(model, kind, share, seed, blk, [t.column(c).to_numpy() for c in coords(d)], t.column("u").to_numpy(), t.column("sgn").to_numpy())
        return _ROWS.empty_table() if got is None else pa.Table.from_arrays(list(record(blk, got)), schema=_ROWS)

    q = points.count() if total is None else total
    kept = of_drawn_blocks(mixing.blocks(src, b, seed, q), share, kind, b, seed, q)
    return kept.groupBy("blk").applyInArrow(run, "h double, blk long, out int, row array<double>")


def global_outputs(points: DataFrame, q: int, s: int, seed: int = 0) -> list[int]:
    """The s of q outputs whose draws are smallest, in order of the draws."""
    spark = points.sparkSession
    drawn = spark.range(q).select("id", hash_int(F.concat(F.lit("0-"), F.col("id").cast("string")), seed).alias("h"))
    return [r["id"] for r in drawn.orderBy("h", "id").limit(s).collect()]


def global_rows(points: DataFrame, model: FunctionalTucker, s: int, seed: int = 0, total: int | None = None, length: int = 1024) -> tuple[np.ndarray, np.ndarray]:
    """s rows of one Fourier transform over all points, in two steps: points are dealt to residue classes of about ``length`` rows (a shuffle of narrow rows), each class is transformed, turned and added to its task's s x (R + 1) block. Rows of no point (the last of a class) are zero."""
    d, r = model.d, model.R
    n = points.count() if total is None else total
    if not n:
        return np.zeros((0, r)), np.zeros(0)
    q2 = max(1, -(-n // length))  # classes
    q1 = -(-n // q2)
    q = q1 * q2
    outputs = np.array(global_outputs(points, q, min(s, q), seed))
    freq = (outputs + 1) // 2
    edge = (outputs == 0) | ((q % 2 == 0) & (outputs == q - 1))
    real = (outputs % 2 == 1) | edge
    scale = np.where(edge, 1.0, np.sqrt(2.0)) / np.sqrt(q)
    rows = mixing.numbered(mixing.signs(points.select("pt_key", *coords(d), "u"), seed), seed).withColumn("cls", F.pmod("q", F.lit(q2)))
    dealt = rows.repartition("cls").sortWithinPartitions("cls", "q")

    def make(batches):
        out, held = None, None

        def add(t: pa.Table) -> None:
            cls = int(t.column("cls")[0].as_py())
            w = np.zeros((q1, r + 1))
            at = t.column("q").to_numpy() // q2
            w[at] = np.concatenate([model.design([t.column(c).to_numpy() for c in coords(d)]), t.column("u").to_numpy()[:, None]], axis=1) * t.column("sgn").to_numpy()[:, None]
            part = np.fft.fft(w, axis=0)[freq % q1] * np.exp(-2j * np.pi * ((cls * freq) % q) / q)[:, None]
            out[...] += scale[:, None] * np.where(real[:, None], part.real, part.imag)

        for batch in batches:
            out = np.zeros((len(outputs), r + 1)) if out is None else out
            t = pa.Table.from_batches([batch]) if held is None else pa.concat_tables([held, pa.Table.from_batches([batch])])
            cls = t.column("cls").to_numpy()
            ends = np.flatnonzero(np.diff(cls)) + 1
            for i, j in zip(np.concatenate([[0], ends[:-1]]) if len(ends) else [], ends):
                add(t.slice(int(i), int(j - i)))
            held = t.slice(int(ends[-1]) if len(ends) else 0)
        if held is not None and held.num_rows:
            add(held)
        return out

    got = sum_blocks(dealt, make, (len(outputs), r + 1))
    return got[:, :r], got[:, r]


_ROWS = pa.schema([("h", pa.float64()), ("blk", pa.int64()), ("out", pa.int32()), ("row", pa.list_(pa.float64()))])


def collect_sketch(rows: DataFrame, s: int, r: int) -> tuple[np.ndarray, np.ndarray]:
    """Matrix and right side of the s rows of smallest draw, in that order."""
    if s * (r + 1) * 8 > MAX_SKETCH:
        raise ValueError(f"a sketch of {s} x {r + 1} numbers is more than {MAX_SKETCH} bytes")
    got = rows.orderBy("h", "blk", "out").limit(s).select("h", "blk", "out", "row").toArrow()
    if not got.num_rows:
        return np.zeros((0, r)), np.zeros(0)
    order = np.lexsort((got.column("out").to_numpy(), got.column("blk").to_numpy(), got.column("h").to_numpy()))
    m = got.column("row").combine_chunks().flatten().to_numpy().reshape(-1, r + 1)[order]
    return m[:, :r], m[:, r]


def sketch(points: DataFrame, model: FunctionalTucker, s: int, kind: str = "dft", b: int = 1024, scope: str = "block", seed: int = 0, total: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """s uniformly drawn mixed rows."""
    q = points.count() if total is None else total
    if scope == "global":
        if kind != "dft":
            raise ValueError("one transform over all rows is the Fourier transform")
        if s * (model.R + 1) * 8 > MAX_SKETCH:
            raise ValueError(f"a sketch of {s} x {model.R + 1} numbers is more than {MAX_SKETCH} bytes: use scope='block'")
        return global_rows(points, model, s, seed, q)
    return collect_sketch(mixed_rows(points, model, share_of(s, q), kind, b, scope, seed, q), s, model.R)


def solve_sketch(points: DataFrame, model: FunctionalTucker, s: int, kind: str = "dft", b: int = 1024, scope: str = "block", seed: int = 0, total: int | None = None, max_bytes: int | None = None) -> Solution:
    """The core from s mixed rows. A sketch of over ``MAX_SKETCH`` bytes is written to the shared folder (about s rows: all whose draw is below the share) and solved there."""
    r = model.R
    if s * (r + 1) * 8 <= (MAX_SKETCH if max_bytes is None else max_bytes):
        a, rhs = sketch(points, model, s, kind, b, scope, seed, total)
        x = solve_small(a, rhs) if len(rhs) else model.core.ravel()
        res = rhs - a @ x if len(rhs) else rhs
        return Solution(x, float(res @ res), float(rhs @ rhs), float("nan"), len(rhs), len(rhs) < r)
    if scope == "global":
        raise ValueError(f"a sketch of {s} x {r + 1} numbers is more than {MAX_SKETCH} bytes: use scope='block'")
    q = points.count() if total is None else total
    rows = cut(mixed_rows(points, model, min(1.0, s / max(q, 1)), kind, b, scope, seed, q).select("row"), "sketch")
    got = lsqr_rows(rows, r, Kronecker(axis_grams(points, model)))
    discard(rows)
    if not got.converged:
        raise RuntimeError(f"the sketched core did not settle in {got.rounds} rounds: take more rows than {got.rows}")
    return got


# -- leverage ---------------------------------------------------------------------------------


def triangular(g: np.ndarray) -> np.ndarray:
    """A matrix whose product with a design row has the row's leverage as its squared norm (directions without weight are left out)."""
    w, v = np.linalg.eigh(g)
    keep = w > max(w[-1], 0) * 1e-13 * len(w)
    return v[:, keep] / np.sqrt(w[keep])


def leverage(points: DataFrame, model: FunctionalTucker) -> DataFrame:
    """points with lev, the exact leverage score of each design row: a Gram scan, then a map. The scores sum to the rank."""
    g, _, _, _ = moments(points, model)
    t, d = triangular(g), model.d
    names = points.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, model.R):
                x = model.design(columns(part, d)) @ t
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array((x * x).sum(axis=1))], names=[*names, "lev"])

    return points.mapInArrow(run, _with(points, "lev"))


def _with(df: DataFrame, name: str):
    from pyspark.sql import types as T

    return T.StructType([*df.schema.fields, T.StructField(name, T.DoubleType())])


def product_leverage(points: DataFrame, model: FunctionalTucker) -> DataFrame:
    """points with lev_proxy, the product over axes of leverages at the nodes; exact on a whole product grid, cheap everywhere (no Gram scan)."""
    turns = []
    for k, a in enumerate(model.axes):
        m = model.mode_values(k, np.linspace(a.lo, a.hi, max(a.nodes, 2)))
        turns.append(triangular(m.T @ m))
    d, names = model.d, points.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = np.ones(batch.num_rows)
            for k, c in enumerate(columns(batch, d)):
                x = model.mode_values(k, c) @ turns[k]
                out *= (x * x).sum(axis=1)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out)], names=[*names, "lev_proxy"])

    return points.mapInArrow(run, _with(points, "lev_proxy"))


def mixed_leverage(points: DataFrame, model: FunctionalTucker, kind: str = "dft", b: int = 1024, seed: int = 0) -> DataFrame:
    """blk, out, lev: leverage of every mixed row. The Gram matrix is that of the rows before mixing, which is unitary."""
    g, _, _, _ = moments(points, model)
    t, r = triangular(g), model.R
    rows = mixed_rows(points, model, float("inf"), kind, b, seed=seed)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            m = batch.column("row").flatten().to_numpy().reshape(-1, r + 1)[:, :r] @ t
            yield pa.RecordBatch.from_arrays([batch.column("blk"), batch.column("out"), pa.array((m * m).sum(axis=1))], names=["blk", "out", "lev"])

    return rows.mapInArrow(run, "blk long, out int, lev double")


def leverage_ls(points: DataFrame, model: FunctionalTucker, s: int, seed: int = 0, proxy: bool = False) -> np.ndarray:
    """Least squares on rows drawn with probability in proportion to leverage, each scaled by 1 / sqrt(probability)."""
    lev = product_leverage(points, model) if proxy else leverage(points, model)
    name = "lev_proxy" if proxy else "lev"
    total = lev.agg(F.sum(name)).first()[0] or 1.0
    p = F.least(F.lit(1.0), F.col(name) * F.lit(s / total))
    rows = lev.withColumn("p", p).where(hash01(F.col("pt_key"), f"lev{seed}") < F.col("p")).select(*coords(model.d), "u", "p").toPandas()
    w = model.design([rows[c].to_numpy() for c in coords(model.d)]) / np.sqrt(rows["p"].to_numpy())[:, None]
    return np.linalg.lstsq(w, rows["u"].to_numpy() / np.sqrt(rows["p"].to_numpy()), rcond=None)[0]


# -- other distance-preserving maps -------------------------------------------------------------


def projected(points: DataFrame, model: FunctionalTucker, s: int, kind: str = "sparse_sign", seed: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """sparse_sign: every row goes with a sign to one of s buckets, which are summed. gauss: s Gaussian combinations of all rows. Each task adds into one s x (R + 1) block."""
    return projections(points, model, [s], kind, seed)[0]


def projections(points: DataFrame, model: FunctionalTucker, sizes: list[int], kind: str = "sparse_sign", seed: int = 0) -> list[tuple[np.ndarray, np.ndarray]]:
    """``projected`` for several s in one scan: buckets of each size, or the first of the most Gaussian combinations (a row's numbers are drawn in order)."""
    d, r = model.d, model.R
    starts = np.cumsum([0, *sizes]) if kind == "sparse_sign" else np.array([0, max(sizes)])
    height = int(starts[-1])
    if height * (r + 1) * 8 > MAX_SKETCH:
        raise ValueError("the sketch is too large for one block")
    src = points.select(*coords(d), "u", mixing.sign_of(F.col("pt_key"), seed).alias("sgn"), hash_int(F.col("pt_key"), f"mix{seed}", 3).alias("bkt"))

    def make(batches):
        out = np.zeros((height, r + 1))
        for batch in batches:
            for part in slices(batch, max(r, max(sizes))):
                w = np.concatenate([model.design(columns(part, d)), part.column("u").to_numpy(zero_copy_only=False)[:, None]], axis=1)
                bkt = part.column("bkt").to_numpy()
                if kind == "sparse_sign":
                    signed = w * part.column("sgn").to_numpy()[:, None]
                    for at, s in zip(starts, sizes):
                        for j in range(r + 1):
                            out[at : at + s, j] += np.bincount(bkt % s, signed[:, j], s)
                elif kind == "gauss":
                    g = np.stack([np.random.default_rng([int(x), seed]).standard_normal(height) for x in bkt], axis=1)
                    out += g @ w
                else:
                    raise ValueError(f"unknown projection {kind!r}")
        return out

    block = sum_blocks(src, make, (height, r + 1))
    block = np.zeros((height, r + 1)) if block is None else block
    parts = [block[at : at + s] for at, s in zip(starts, sizes)] if kind == "sparse_sign" else [block[:s] / np.sqrt(s) for s in sizes]
    return [(x[:, :r], x[:, r]) for x in parts]
