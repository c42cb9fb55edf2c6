"""SimHash near-duplicates by bit-sliced comparison.

Fingerprints: 64 bits over the XXH64 (seed 42) of 3-word shingles. Distinct fingerprints
are dealt into buckets that agree on two of radius + 2 bit blocks, so any two within the
radius meet in at least one bucket. Within a bucket, bit planes stand vertically: one
64-bit word holds one bit of 64 fingerprints, carry-save counters update 64 distances with
a few operations, and queries whose block has wholly exceeded the radius are abandoned.
Each bucket yields a spanning forest of its links, never its pairs; components follow by
minimum labels with pointer jumping over tables in the shared folder.

Scale: copies collapse to one fingerprint before anything is compared. A bucket of over
``BUCKET`` fingerprints is split into chunks, and each pair of chunks is a task's unit, so
no group reaches one task whole. Nothing about documents is collected.

Defined cases: a text without words (or null) has fingerprint zero, linked like any other;
fewer than three words: the whole sequence is the one shingle; repeated rows link to each
other; a null id takes no part in the minimum; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import discard, map_batches, small, written

RADIUS = 3
WIDTH = 3
BUCKET = 2048
SMALL_GROUP = 16
PLANES_AT_ONCE = 8


# -- fingerprints ------------------------------------------------------------------------


def fingerprint(text: str | None, width: int = WIDTH) -> int:
    """The fingerprint as an unsigned integer. A bit is set if it is set in over half the shingle hashes."""
    from xxhash import xxh64_intdigest as digest

    words = (text or "").encode("utf-8", "replace").lower().split()
    if not words:
        return 0
    if len(words) <= width:
        shingles: Iterator[bytes] = iter([b" ".join(words)])
        n = 1
    else:
        n = len(words) - width + 1
        shingles = map(b" ".join, zip(*(words[i:] for i in range(width))))
    counts = np.zeros(64, np.int64)
    hashes = np.fromiter((digest(s, 42) for s in shingles), np.uint64, n)
    for i in range(0, n, 1 << 16):
        part = hashes[i : i + (1 << 16)]
        counts += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * counts > n, bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH) -> DataFrame:
    """doc_id, fp (the 64 bits as a signed long)."""
    src = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    schema = T.StructType([src.schema["doc_id"], T.StructField("fp", T.LongType())])

    def work():
        def act(batch: pa.RecordBatch) -> dict:
            got = np.array([fingerprint(t, width) for t in batch.column("text").to_pylist()], np.uint64)
            return {"doc_id": batch.column("doc_id"), "fp": pa.array(got.view(np.int64))}

        return act

    return map_batches(src, work, schema)


# -- bit-sliced comparison ---------------------------------------------------------------


def planes(values: np.ndarray) -> np.ndarray:
    """Bit planes: 64 rows of words; bit i of word j of row b is bit b of value 64 j + i."""
    pad = -len(values) % 64
    bits = np.unpackbits(np.concatenate([values, np.zeros(pad, np.uint64)]).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    return np.packbits(np.ascontiguousarray(bits.T), axis=1, bitorder="little").view(np.uint64)


class Counters:
    """Carry-save counters of k bits for many distances; ``far`` marks those over the radius. They start at 2^k - 1 - radius, so that the carry out of the last bit is the mark."""

    def __init__(self, shape, radius: int):
        k = radius.bit_length()
        start = (1 << k) - 1 - radius
        full = ~np.uint64(0)
        self.bits = [np.full(shape, full if start >> i & 1 else 0, np.uint64) for i in range(k)]
        self.far = np.zeros(shape, np.uint64)

    def add(self, x: np.ndarray) -> None:
        for i, b in enumerate(self.bits):
            carry = b & x
            self.bits[i] = b ^ x
            x = carry
        self.far |= x

    def keep(self, rows: np.ndarray) -> None:
        self.bits, self.far = [b[rows] for b in self.bits], self.far[rows]


def near_rows(queries: np.ndarray, block: np.ndarray, radius: int) -> np.ndarray:
    """For each query, words whose bits tell which fingerprints of the block (as planes) are within the radius."""
    out = np.zeros((len(queries), block.shape[1]), np.uint64)
    alive = np.arange(len(queries))
    count = Counters((len(queries), block.shape[1]), radius)
    full = ~np.uint64(0)
    for b in range(64):
        flip = np.where(queries[alive] >> np.uint64(b) & np.uint64(1), full, np.uint64(0))
        count.add(block[b][None, :] ^ flip[:, None])
        if b % PLANES_AT_ONCE == PLANES_AT_ONCE - 1 and b < 63:
            open_ = (count.far != full).any(axis=1)
            if not open_.all():
                alive = alive[open_]
                count.keep(open_)
                if not len(alive):
                    return out
    out[alive] = ~count.far
    return out


def near_pairs(a: np.ndarray, b: np.ndarray, radius: int) -> np.ndarray:
    """Whether a[i] and b[i] are within the radius; 64 pairs to a word."""
    x = planes(a ^ b)
    count = Counters(x.shape[1], radius)
    for row in x:
        count.add(row)
    return np.unpackbits((~count.far).view(np.uint8), bitorder="little")[: len(a)].astype(bool)


def group_roots(values: np.ndarray, radius: int) -> np.ndarray:
    """For each value of one group the index of its component's first member."""
    m = len(values)
    block = planes(values)
    near = np.concatenate([near_rows(values[i : i + 1024], block, radius) for i in range(0, m, 1024)])
    tail = m % 64
    if tail:
        near[:, -1] &= np.uint64((1 << tail) - 1)
    root = np.full(m, -1, np.int64)
    for seed in range(m):
        if root[seed] >= 0:
            continue
        seen = near[seed].copy()
        members = np.flatnonzero(np.unpackbits(seen.view(np.uint8), bitorder="little")[:m])
        while len(members):
            root[members] = seed
            more = np.bitwise_or.reduce(near[members], axis=0) & ~seen
            seen |= more
            members = np.flatnonzero(np.unpackbits(more.view(np.uint8), bitorder="little")[:m])
        root[seed] = seed
    return root


def forest(group: np.ndarray, values: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Edges (member, root) of a spanning forest of the links within groups; rows of a group stand together."""
    n = len(values)
    start = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]]))
    size = np.diff(np.append(start, n))
    a, b = [], []
    little = np.repeat((size > 1) & (size <= SMALL_GROUP), size)
    of = np.repeat(np.arange(len(start)), size)
    left, right = [], []
    for off in range(1, SMALL_GROUP):
        i = np.flatnonzero(little[: n - off] & (of[: n - off] == of[off:]))
        if not len(i):
            break
        left.append(i)
        right.append(i + off)
    if left:
        i, j = np.concatenate(left), np.concatenate(right)
        ok = near_pairs(values[i], values[j], radius)
        i, j = i[ok], j[ok]
        label = np.arange(n)
        while True:
            low = np.minimum(label[i], label[j])
            before = label.copy()
            np.minimum.at(label, i, low)
            np.minimum.at(label, j, low)
            label = label[label]
            if (label == before).all():
                break
        hit = np.flatnonzero(label != np.arange(n))
        a.append(values[hit])
        b.append(values[label[hit]])
    for s, m in zip(start[size > SMALL_GROUP], size[size > SMALL_GROUP]):
        part = values[s : s + m]
        root = group_roots(part, radius)
        hit = np.flatnonzero(root != np.arange(m))
        a.append(part[hit])
        b.append(part[root[hit]])
    none = np.zeros(0, np.uint64)
    return np.concatenate(a or [none]), np.concatenate(b or [none])


# -- plans -------------------------------------------------------------------------------


def bucket_keys(fp, radius: int = RADIUS):
    """One long for each way to agree on two of radius + 2 blocks."""
    n = radius + 2
    cut = [64 * i // n for i in range(n + 1)]
    part = [F.shiftrightunsigned(fp, cut[i]).bitwiseAND(F.lit((1 << (cut[i + 1] - cut[i])) - 1)) for i in range(n)]
    width = max(cut[i + 1] - cut[i] for i in range(n))
    return F.array(*[F.shiftleft(F.shiftleft(F.lit(t).cast("long"), width) + part[i], width) + part[j] for t, (i, j) in enumerate(combinations(range(n), 2))])


def links(prints: DataFrame, radius: int = RADIUS, bucket: int = BUCKET) -> DataFrame:
    """Forest edges (a, b) between distinct fingerprints (column fp) within the radius."""
    rows = prints.select("fp", F.explode(bucket_keys(F.col("fp"), radius)).alias("key"))
    hot = written(rows.groupBy("key").count().filter(F.col("count") > bucket).select("key", F.ceil(2 * F.col("count") / bucket).cast("int").alias("chunks")), "hot-buckets")
    joined = rows.join(F.broadcast(hot) if small(hot) else hot, "key", "left")
    chunk = F.pmod(F.xxhash64("fp"), F.col("chunks")).cast("int")
    lo, hi = F.least(chunk, F.col("other")), F.greatest(chunk, F.col("other"))
    dealt = (
        joined.withColumn("other", F.explode(F.when(F.col("chunks").isNull(), F.array(F.lit(-1))).otherwise(F.sequence(F.lit(0), F.col("chunks") - 1))))
        .withColumn("unit", F.when(F.col("other") < 0, F.lit(-1).cast("long")).otherwise(lo.cast("long") * 2**31 + hi))
        .filter((F.col("other") < 0) | (chunk != F.col("other")))
        .select("key", "unit", "fp")
    )
    parts = int(prints.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ordered = dealt.repartition(parts, "key", "unit").sortWithinPartitions("key", "unit")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept = [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint64)]

        def edges(key, unit, fp):
            group = np.cumsum(np.concatenate([[0], (key[1:] != key[:-1]) | (unit[1:] != unit[:-1])])) if len(key) else key
            a, b = forest(group, fp, radius)
            return pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["a", "b"])

        for batch in batches:
            new = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(3)]
            new[2] = new[2].astype(np.int64).view(np.uint64)
            key, unit, fp = (np.concatenate([x, y]) for x, y in zip(kept, new))
            if not len(key):
                continue
            end = len(key) - 1
            change = np.flatnonzero((key[1:] != key[:-1]) | (unit[1:] != unit[:-1]))
            cut = int(change[-1]) + 1 if len(change) else 0
            kept = [key[cut:], unit[cut:], fp[cut:]]
            if cut and end:
                yield edges(key[:cut], unit[:cut], fp[:cut])
        if len(kept[0]) > 1:
            yield edges(*kept)

    return ordered.mapInArrow(run, "a long, b long").distinct()


def components(edges: DataFrame) -> DataFrame:
    """(node, label) for every node of the edges (a, b): label is the component's smallest node. Each round takes neighbours' smallest labels and then follows labels twice; tables are cut in the shared folder."""
    spark = edges.sparkSession
    both = written(edges.select(F.col("a").alias("x"), F.col("b").alias("y")).union(edges.select("b", "a")), "links")
    label = written(both.groupBy(F.col("x").alias("node")).agg(F.min(F.least("x", "y")).alias("label")), "labels")
    while True:
        seen = both.join(label, F.col("x") == F.col("node")).groupBy(F.col("y").alias("node")).agg(F.min("label").alias("seen"))
        lower = written(label.join(seen, "node").select("node", F.least("label", "seen").alias("label"), F.col("label").alias("was")), "labels")
        jump = lower.select(F.col("node").alias("n"), F.col("label").alias("next"))
        after = written(lower.join(jump, F.col("label") == F.col("n")).select("node", F.least("label", "next").alias("label"), "was"), "labels")
        discard(label)
        discard(lower)
        label = after.select("node", "label")
        if after.filter(F.col("label") != F.col("was")).isEmpty():
            return label


def near_duplicates(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS, width: int = WIDTH, bucket: int = BUCKET) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (the smallest id reachable over links)."""
    of_doc = written(fingerprints(docs, id_col=id_col, text_col=text_col, width=width), "fingerprints")
    prints = written(of_doc.groupBy("fp").agg(F.min("doc_id").alias("first")), "prints")
    label = components(links(prints, radius, bucket))
    named = written(prints.join(label, F.col("fp") == F.col("node"), "left").select("fp", "first", F.coalesce("label", "fp").alias("label")), "named")
    least = written(named.groupBy("label").agg(F.min("first").alias("component_id")), "components")
    of_print = written(named.join(least, "label").select("fp", "component_id"), "of-print")
    return of_doc.join(of_print, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", **kw) -> DataFrame:
    """docs without the rows whose id is not their group's smallest. Rows of one id are one document; a null id stays."""
    from .common import without

    found = near_duplicates(docs, id_col=id_col, text_col=text_col, **kw)
    return without(docs, found.filter(F.col("doc_id") != F.col("component_id")).select(F.col("doc_id").alias(id_col)), id_col)
