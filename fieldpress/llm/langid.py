"""Language identification by rank-order profiles of character n-grams.

A profile is the list of a language's most frequent 1- to 3-grams. A document is compared
with each profile by the out-of-place distance of its own most frequent n-grams; the
nearest profile wins. N-grams run over lower-cased letters; each run of other characters
is one boundary.

Training counts n-grams of a bounded sample of labelled rows (``SAMPLE_PER_LANG`` a
language, taken by a hash of the id); counts are combined before the shuffle and profiles
of ``PROFILE`` rows a language reach the driver. Prediction is row by row.

Defined cases: a null text or one without a letter is ``und`` with score 0; equal
distances go to the first language in alphabetical order; n-grams of equal count rank by
code point; rows whose language is null are never learned from; with nothing to learn
from, all is ``und``.
"""

from __future__ import annotations

import sys

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import map_batches

PROFILE = 400
SAMPLE_PER_LANG = 1500
_BOUNDARY = 1
_letters: np.ndarray | None = None


def _letter_table() -> np.ndarray:
    """Code point -> itself if it is a letter, else the boundary."""
    global _letters
    if _letters is None:
        t = np.full(sys.maxunicode + 1, _BOUNDARY, np.int64)
        for i in range(sys.maxunicode + 1):
            if chr(i).isalpha():
                t[i] = i
        _letters = t
    return _letters


def grams(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """Distinct packed n-grams (three 21-bit code points, ascending) and their counts."""
    raw = np.frombuffer((text or "").lower().encode("utf-32-le", "replace"), np.uint32)
    codes = _letter_table()[raw]
    codes = np.concatenate([[_BOUNDARY], codes, [_BOUNDARY]])
    codes = codes[np.concatenate([[True], (codes[1:] != _BOUNDARY) | (codes[:-1] != _BOUNDARY)])]
    if len(codes) < 2:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    one = codes[codes != _BOUNDARY]
    two = (codes[:-1] << 21) | codes[1:]
    three = (codes[:-2] << 42) | (codes[1:-1] << 21) | codes[2:]
    packed = np.sort(np.concatenate([one, two, three]))
    first = np.flatnonzero(np.concatenate([[True], packed[1:] != packed[:-1]]))
    return packed[first], np.diff(np.append(first, len(packed)))


def top(keys: np.ndarray, counts: np.ndarray, k: int) -> np.ndarray:
    """The k most frequent, in order; equal counts by key."""
    if len(keys) > 4 * k:  # only those that can be among the first k are sorted
        keep = counts >= np.partition(counts, len(counts) - k)[len(counts) - k]
        keys, counts = keys[keep], counts[keep]
    return keys[np.argsort(-counts, kind="stable")][:k]


class Profiles:
    """Rank matrix over the union of all profiles' n-grams."""

    def __init__(self, ranked: dict[str, list[int]], size: int = PROFILE):
        self.langs, self.size = sorted(ranked), size
        self.union = np.unique(np.concatenate([np.array(ranked[x], np.int64) for x in self.langs])) if self.langs else np.zeros(0, np.int64)
        self.ranks = np.full((len(self.langs), len(self.union) + 1), -1, np.int32)
        for i, x in enumerate(self.langs):
            self.ranks[i, np.searchsorted(self.union, np.array(ranked[x], np.int64))] = np.arange(len(ranked[x]))

    def predict(self, text: str | None) -> tuple[str, float]:
        best = top(*grams(text), self.size)
        if not len(best) or not self.langs:
            return "und", 0.0
        at = np.searchsorted(self.union, best)
        at[at == len(self.union)] = 0
        at = np.where(self.union[at] == best, at, len(self.union))
        ranks = self.ranks[:, at]
        away = np.where(ranks < 0, self.size, np.abs(ranks - np.arange(len(best), dtype=np.int32))).sum(axis=1)
        i = int(np.argmin(away))
        return self.langs[i], 1.0 - float(away[i]) / (self.size * len(best))


def learn(docs: DataFrame, *, text_col: str = "text", lang_col: str = "lang", id_col: str = "doc_id", per_lang: int = SAMPLE_PER_LANG, size: int = PROFILE) -> Profiles:
    """Profiles from at most about ``per_lang`` rows of each language: those whose id hashes lowest, by the share that the language's row count gives."""
    labelled = docs.filter(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull())
    totals = {r[0]: r[1] for r in labelled.groupBy(lang_col).count().collect()}
    share = F.lit(0.0)
    for lang, n in totals.items():
        share = F.when(F.col(lang_col) == lang, F.lit(min(1.0, per_lang / n))).otherwise(share)
    place = F.pmod(F.xxhash64(F.col(id_col).cast("string")), F.lit(1 << 20)) / float(1 << 20)
    sample = labelled.filter(place < share).select(F.col(lang_col).alias("lang"), F.col(text_col).alias("text"))

    def work():
        def act(batch: pa.RecordBatch) -> dict:
            by: dict[str, list] = {}
            for lang, text in zip(batch.column("lang").to_pylist(), batch.column("text").to_pylist()):
                by.setdefault(lang, []).append(grams(text))
            langs, keys, counts = [], [], []
            for lang, found in by.items():
                k, inv = np.unique(np.concatenate([x[0] for x in found]), return_inverse=True)
                c = np.bincount(inv, np.concatenate([x[1] for x in found]), len(k))
                langs += [lang] * len(k)
                keys.append(k)
                counts.append(c)
            none = np.zeros(0)
            return {"lang": langs, "gram": np.concatenate(keys or [none]).astype(np.int64), "n": np.concatenate(counts or [none]).astype(np.int64)}

        return act

    schema = T._parse_datatype_string("lang string, gram long, n long")
    counted = map_batches(sample, work, schema).groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    from pyspark.sql import Window

    w = Window.partitionBy("lang").orderBy(F.desc("n"), F.asc("gram"))
    rows = counted.withColumn("r", F.row_number().over(w)).filter(F.col("r") <= size).select("lang", "gram", "r").collect()
    ranked: dict[str, list] = {}
    for r in sorted(rows, key=lambda r: (r.lang, r.r)):
        ranked.setdefault(r.lang, []).append(r.gram)
    return Profiles(ranked, size)


def identify(docs: DataFrame, profiles: Profiles, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, lang_pred, score (1 less the distance over its largest value)."""
    src = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    schema = T.StructType([src.schema["doc_id"], T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])

    def work():
        def act(batch: pa.RecordBatch) -> dict:
            found = [profiles.predict(t) for t in batch.column("text").to_pylist()]
            return {"doc_id": batch.column("doc_id"), "lang_pred": [x[0] for x in found], "score": [x[1] for x in found]}

        return act

    return map_batches(src, work, schema)
