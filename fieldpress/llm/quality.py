"""Quality classifier: a factorisation machine.

Features of a whole text: hashed words (log counts, scaled to unit length), statistics of
structure (shares of symbols, capitals, repeats, ...; cut into steps), and bucketed
metadata. The score is sigmoid(w0 + w.x + sum of pairwise interactions), the interactions
of rank ``RANK`` by the sum-of-squares identity, so linear in the features.

Training takes about ``SAMPLE`` labelled rows at most, the share whose id (and, where ids
repeat, text) hashes lowest; their features are made on the executors and fitted on the
driver (bounded). Scoring is row
by row.

Defined cases: a null or empty text has the structure features of an empty text and is
scored like any; a machine scores with the metadata that it was learned with, and null or
no metadata (a column that the table lacks, or not a number) is a bucket of its own; rows
with a null label or id are not learned from; without labels of both kinds the score is the prior (0.5 with none).
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import map_batches, unused

SAMPLE = 6000
BITS = 14
RANK = 8
STEPS = 16
#: Words whose slots are kept, for speed only.
SLOTS = 100_000
_SYMBOLS = "#*$%&|<>!=@^~_{}[]\\"
_STATS = ("words", "symbols", "capitals", "digits", "repeats", "kinds", "length", "lines", "dup_lines", "ends", "longest", "letters", "pipes")


class Features:
    """Indices and values of one text. Slots: words by hash, then statistics by step, then metadata."""

    def __init__(self, bits: int = BITS, n_meta: int = 0):
        self.bits, self.n_meta = bits, n_meta
        self.size = (1 << bits) + STEPS * (len(_STATS) + n_meta)
        self.slots: dict[str, int] = {}

    def slot(self, word: str) -> int:
        if len(self.slots) > SLOTS:
            self.slots.clear()
        got = self.slots.get(word)
        if got is None:
            got = self.slots[word] = zlib.crc32(word.encode("utf-8", "replace")) & ((1 << self.bits) - 1)
        return got

    def __call__(self, text: str | None, meta: tuple = ()) -> tuple[np.ndarray, np.ndarray]:
        text = text or ""
        words = text.split()
        slot, slots = self.slot, self.slots
        ids = np.fromiter((slots[w] if w in slots else slot(w) for w in words), np.int32, len(words))
        kinds, counts = np.unique(ids, return_counts=True)
        value = np.log1p(counts.astype(np.float32))
        if len(value):
            value /= np.sqrt((value * value).sum())
        steps = np.array([min(STEPS - 1, int(x * STEPS)) for x in self.stats(text, words, ids)] + [STEPS - 1 if m is None else min(STEPS - 2, max(0, int(math.log1p(abs(m))))) for m in meta], np.int32)
        at = (1 << self.bits) + STEPS * np.arange(len(steps), dtype=np.int32) + steps
        return np.concatenate([kinds, at]).astype(np.int32), np.concatenate([value, np.full(len(at), 0.5, np.float32)]).astype(np.float32)

    @staticmethod
    def stats(text: str, words: list[str], ids: np.ndarray) -> list[float]:
        n, w = max(1, len(text)), max(1, len(words))
        lines = text.split("\n")
        full = [x for x in lines if x]
        grow = lambda x, top: min(1.0, math.log1p(x) / top)
        symbols = sum(map(text.count, _SYMBOLS))
        bare = text.encode("utf-8", "replace")
        capitals = len(bare) - len(bare.translate(None, b"ABCDEFGHIJKLMNOPQRSTUVWXYZ"))
        digits = len(bare) - len(bare.translate(None, b"0123456789"))
        letters = len(bare.translate(None, b" \t\r\n0123456789!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"))
        repeats = int((ids[1:] == ids[:-1]).sum())
        return [
            grow(len(words), 10.0),
            min(1.0, 6 * symbols / n),
            min(1.0, 1.5 * capitals / n),
            min(1.0, 5 * digits / n),
            min(1.0, 3 * repeats / w),
            len(np.unique(ids)) / w,
            min(1.0, n / w / 16),
            grow(len(full), 7.0),
            1 - len(set(full)) / len(full) if full else 0.0,
            sum(x.rstrip()[-1:] in ".!?" for x in full) / len(full) if full else 0.0,
            min(1.0, max(map(len, words), default=0) / 64),
            letters / max(1, len(bare)),
            min(1.0, 20 * text.count("|") / n),
        ]


class Machine:
    def __init__(self, size: int, rank: int = RANK, seed: int = 7, metadata: tuple[str, ...] = ()):
        rng = np.random.default_rng(seed)
        self.metadata = tuple(metadata)
        self.w0, self.w = 0.0, np.zeros(size, np.float32)
        self.v = rng.normal(0, 0.02, (size, rank)).astype(np.float32)

    def margin(self, idx: np.ndarray, val: np.ndarray) -> float:
        vx = self.v[idx] * val[:, None]
        s = vx.sum(axis=0)
        return float(self.w0 + self.w[idx] @ val + 0.5 * ((s * s).sum() - (vx * vx).sum()))

    def fit(self, rows: list[tuple[np.ndarray, np.ndarray]], y: np.ndarray, epochs: int = 12, batch: int = 64, rate: float = 0.02, decay: float = 1e-5, seed: int = 7) -> "Machine":
        """Adagrad on the logistic loss, in an order that depends on the seed alone."""
        if len(y) == 0:
            return self
        p = float(np.clip(y.mean(), 1e-3, 1 - 1e-3))
        self.w0 = math.log(p / (1 - p))
        if y.min() == y.max():
            return self
        gw, gv, g0, rng = np.full_like(self.w, 1e-6), np.full_like(self.v, 1e-6), 1e-6, np.random.default_rng(seed)
        lens = np.array([len(r[0]) for r in rows])
        for _ in range(epochs):
            order = rng.permutation(len(y))
            for i in range(0, len(order), batch):
                some = order[i : i + batch]
                idx, val = np.concatenate([rows[j][0] for j in some]), np.concatenate([rows[j][1] for j in some])
                at = np.concatenate([[0], np.cumsum(lens[some])[:-1]])
                vx = self.v[idx] * val[:, None]
                s = np.add.reduceat(vx, at, axis=0)
                m = self.w0 + np.add.reduceat(self.w[idx] * val, at) + 0.5 * ((s * s).sum(1) - np.add.reduceat((vx * vx).sum(1), at))
                err = (1 / (1 + np.exp(-np.clip(m, -30, 30))) - y[some]).astype(np.float32) / len(some)
                row = np.repeat(np.arange(len(some)), lens[some])
                e = err[row] * val
                kinds, inv = np.unique(idx, return_inverse=True)
                dw = np.bincount(inv, e, len(kinds)).astype(np.float32) + decay * self.w[kinds]
                dv_rows = e[:, None] * (s[row] - vx)
                dv = np.stack([np.bincount(inv, dv_rows[:, k], len(kinds)) for k in range(dv_rows.shape[1])], 1).astype(np.float32) + decay * self.v[kinds]
                d0 = float(err.sum())
                g0 += d0 * d0
                gw[kinds] += dw * dw
                gv[kinds] += dv * dv
                self.w0 -= rate * d0 / math.sqrt(g0)
                self.w[kinds] -= 4 * rate * dw / np.sqrt(gw[kinds])
                self.v[kinds] -= rate * dv / np.sqrt(gv[kinds])
        return self


def _metadata(docs: DataFrame, names: tuple[str, ...]) -> list:
    return [F.col(f"`{m}`").try_cast("double") if m in docs.columns else F.lit(None).cast("double") for m in names]


def learn(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", metadata: tuple[str, ...] = (), sample: int = SAMPLE, bits: int = BITS) -> Machine:
    """Fits on about ``sample`` labelled rows at most. ``labels`` holds the rows that may be learned from."""
    usable = labels.filter(F.col(id_col).isNotNull() & F.col(label_col).isin(0, 1)).groupBy(F.col(id_col).alias("k")).agg(F.max(label_col).cast("int").alias("y"))
    share = sample / max(1, usable.count())
    picked = usable.filter(F.pmod(F.xxhash64(F.col("k").cast("string")), F.lit(1 << 30)) / float(1 << 30) < share)
    src = docs.select(F.col(id_col).alias("k"), F.col(text_col).alias("text"), *[c.alias(f"m{i}") for i, c in enumerate(_metadata(docs, metadata))])
    joined = src.join(F.broadcast(picked), "k")
    # ids may repeat in docs: the rows are counted (ids alone are read) and thinned by their texts' hashes
    rows = docs.select(F.col(id_col).alias("k")).join(F.broadcast(picked), "k").count()
    if rows > 2 * sample:
        joined = joined.filter(F.pmod(F.xxhash64("text"), F.lit(1 << 30)) / float(1 << 30) < sample / rows).dropDuplicates(["k", "text"])
    schema = T._parse_datatype_string("y int, h long, idx binary, val binary")

    def work():
        feats = Features(bits, len(metadata))

        def act(batch: pa.RecordBatch) -> dict:
            cols = [batch.column(n).to_pylist() for n in batch.schema.names]
            names = batch.schema.names
            get = dict(zip(names, cols))
            out = [feats(t, tuple(get[f"m{j}"][i] for j in range(len(metadata)))) for i, t in enumerate(get["text"])]
            return {"y": get["y"], "h": [zlib.crc32(str(k).encode()) for k in get["k"]], "idx": [x[0].tobytes() for x in out], "val": [x[1].tobytes() for x in out]}

        return act

    rows = sorted((r.h, r.idx, r.val, r.y) for r in map_batches(joined, work, schema).collect())
    data = [(np.frombuffer(r[1], np.int32), np.frombuffer(r[2], np.float32)) for r in rows]
    return Machine(Features(bits, len(metadata)).size, metadata=metadata).fit(data, np.array([r[3] for r in rows], np.float32))


def score(docs: DataFrame, machine: Machine, *, id_col: str = "doc_id", text_col: str = "text", bits: int = BITS) -> DataFrame:
    """doc_id and score (0 to 1) of every row."""
    src = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), *[c.alias(f"m{i}") for i, c in enumerate(_metadata(docs, machine.metadata))])
    schema = T.StructType([src.schema["doc_id"], T.StructField("score", T.DoubleType())])
    return map_batches(src, lambda: _score_batch(machine, bits, "doc_id"), schema)


def _score_batch(machine: Machine, bits: int, id_name: str):
    n_meta = len(machine.metadata)
    feats = Features(bits, n_meta)

    def act(batch: pa.RecordBatch) -> dict:
        meta = [batch.column(f"m{j}").to_pylist() for j in range(n_meta)]
        out = []
        for i, t in enumerate(batch.column("text").to_pylist()):
            m = machine.margin(*feats(t, tuple(x[i] for x in meta)))
            out.append(1 / (1 + math.exp(-max(-30.0, min(30.0, m)))))
        return {id_name: batch.column(id_name), "score": out}

    return act


def keep_good(docs: DataFrame, machine: Machine, threshold: float, *, text_col: str = "text", bits: int = BITS) -> DataFrame:
    """The rows of docs with a score of at least ``threshold``, with all their columns and no shuffle."""
    (name,) = unused(docs, "quality_score")
    n_meta = len(machine.metadata)

    @F.pandas_udf("double")
    def marks(batches: Iterator[tuple[pd.Series, ...]]) -> Iterator[pd.Series]:
        feats = Features(bits, n_meta)
        for texts, *meta in batches:
            found = [machine.margin(*feats(t, tuple(None if pd.isna(x) else float(x) for x in m))) for t, *m in zip(texts, *meta[:n_meta])]
            yield pd.Series(1 / (1 + np.exp(-np.clip(np.array(found, float), -30, 30))))

    # a second column even without metadata: the iterator then always holds tuples
    cols = [F.col(text_col), *(_metadata(docs, machine.metadata) or [F.lit(0.0)])]
    return docs.withColumn(name, marks(*cols)).filter(F.col(name) >= threshold).drop(name)
