"""Signs, blocks and block transforms of rows, all determined by one hash of the point key: its parts give block, position, sign and bucket."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import mixers
from .sampling import hash_int


def sign_of(key: Column, seed: int | str = 0) -> Column:
    """+1 or -1 with probability one half, by hash parity."""
    return (1 - 2 * F.pmod(hash_int(key, f"mix{seed}", 2), F.lit(2))).cast("int")


def signs(points: DataFrame, seed: int | str = 0) -> DataFrame:
    return points.withColumn("sgn", sign_of(F.col("pt_key"), seed))


def blocks(points: DataFrame, b: int, seed: int | str = 0, total: int | None = None) -> DataFrame:
    """Adds blk and h (order within the block): blocks of about b rows by hash. A shuffle of narrow rows follows when they are gathered."""
    n = points.count() if total is None else total
    count = max(1, (2 * n + b) // (2 * b))  # halves go up, as in SQL
    return points.withColumn("blk", F.pmod(hash_int(F.col("pt_key"), f"mix{seed}", 0), F.lit(count)).cast("long")).withColumn("h", hash_int(F.col("pt_key"), f"mix{seed}", 1))


def numbered(points: DataFrame, seed: int | str = 0) -> DataFrame:
    """Adds q: the place of each row (from 0) in the order of the hash of its key, ties by key, coordinates and value. One shuffle by ranges; a count a partition reaches the driver."""
    from .storage import cut

    ties = ["pt_key", *[c for c in points.columns if c == "u" or c[0] == "c" and c[1:].isdigit()]]
    hashed = points.withColumn("h", hash_int(F.col("pt_key"), f"mix{seed}", 1))
    ranged = cut(hashed.repartitionByRange("h").sortWithinPartitions("h", *ties).withColumn("part", F.spark_partition_id()).withColumn("at", F.monotonically_increasing_id() - F.shiftleft(F.spark_partition_id().cast("long"), 33)), "numbered")
    sizes = {r["part"]: r["count"] for r in ranged.groupBy("part").count().collect()}
    before = np.concatenate([[0], np.cumsum([sizes.get(i, 0) for i in range(max(sizes, default=-1) + 1)])]).tolist()
    return ranged.withColumn("q", F.element_at(F.array(*[F.lit(int(x)) for x in before]), F.col("part") + 1) + F.col("at")).drop("part", "at", "h")


def positions(blocked: DataFrame) -> DataFrame:
    """Adds pos, the place in the block (from 0). Rows of equal keys are ordered by their coordinates and value."""
    ties = [c for c in blocked.columns if c == "u" or c[0] == "c" and c[1:].isdigit()]
    w = Window.partitionBy("blk").orderBy("h", "pt_key", *ties)
    return blocked.withColumn("pos", F.row_number().over(w) - 1)


def mix_values(rows: DataFrame, kind: str, value: str = "x") -> DataFrame:
    """blk, out, y: the transform of each block of (blk, pos, value); the row count of a block is its length."""

    def run(table: pa.Table) -> pa.Table:
        t = table.sort_by("pos")
        y = mixers.mix(t.column(value).to_numpy().astype(float)[:, None], kind)[:, 0]
        return pa.table({"blk": t.column("blk").combine_chunks(), "out": pa.array(np.arange(len(y)), pa.int32()), "y": pa.array(y)})

    return rows.select("blk", "pos", value).groupBy("blk").applyInArrow(run, f"blk {rows.schema['blk'].dataType.simpleString()}, out int, y double")


def factored_dft(rows: DataFrame, q1: int, q2: int, freqs: list[int], value: str = "x", index: str = "q") -> DataFrame:
    """f, re, im: one unitary DFT over q1 * q2 rows (missing ones are 0) for the wanted frequencies, in two steps: within each residue class (shuffle), then over classes (an aggregate)."""
    wanted = np.array(sorted(freqs))

    def run(table: pa.Table) -> pa.Table:
        q = table.column(index).to_numpy()
        x = np.zeros(q1)
        x[q // q2] = table.column(value).to_numpy()
        cls = int(q[0] % q2)
        part = np.fft.fft(x)[wanted % q1] * np.exp(-2j * np.pi * cls * wanted / (q1 * q2)) / np.sqrt(q1 * q2)
        return pa.table({"f": pa.array(wanted, pa.int64()), "re": pa.array(part.real), "im": pa.array(part.imag)})

    parts = rows.groupBy(F.pmod(F.col(index), F.lit(q2)).alias("cls")).applyInArrow(run, "f long, re double, im double")
    return parts.groupBy("f").agg(F.sum("re").alias("re"), F.sum("im").alias("im"))


