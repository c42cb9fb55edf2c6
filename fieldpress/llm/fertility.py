"""Quality rules by tokeniser fertility.

Each distinct word of a batch is encoded once by a public vocabulary; a document's
characters per token, byte-fallback share and token entropy are weighted sums over its
words. A document outside the band of its language and length (``judge_fitted``) or its
script is rejected. Word counts, repeated lines and repeated word windows are measured in
the same pass.

Row by row; fitted bands take one small aggregation over the measured rows, written once
without the texts. Memory is bounded by a slice of texts and a vocabulary cache of
``CACHE_WORDS`` words that is emptied when full.

Defined cases: a null text counts as no words and fails the base rule; a text without
letters has script ``none``; repeated rows give repeated results; an empty table gives an
empty result; other columns of the input are not read.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import map_batches, written

CACHE_WORDS = 400_000
SYMBOLS = "#*$%&|<>"
SPACES = " \t\n\r\x0b\x0c"


@dataclass(frozen=True)
class Band:
    """Accepted ranges. The entropy floor (bits) counts only from ``entropy_from`` tokens on."""

    chars_per_token: tuple[float, float]
    max_fallback: float
    min_entropy: float
    entropy_from: int = 64


#: Bands by script, for the 32k piece vocabulary; wide enough for any ordinary prose.
SCRIPT_BANDS = {
    "latin": Band((1.5, 8.0), 0.10, 4.0),
    "cyrillic": Band((0.9, 6.0), 0.20, 3.5),
    "greek": Band((0.5, 5.0), 0.60, 3.5),
    "cjk": Band((0.25, 3.0), 0.90, 3.5),
    "other": Band((0.2, 8.0), 0.98, 3.0),
    "none": Band((0.2, 8.0), 0.98, 2.0),
}

_SCRIPTS = (
    ("latin", re.compile("[A-Za-zÀ-ɏḀ-ỿ]")),
    ("cyrillic", re.compile("[Ѐ-ԯ]")),
    ("greek", re.compile("[Ͱ-Ͽἀ-῿]")),
    ("cjk", re.compile("[぀-ヿ㐀-䶿一-鿿가-힯]")),
)

SCHEMA = (
    "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, n_tokens long, "
    "chars_per_token double, fallback_share double, token_entropy double, script string"
)


class PieceVocabulary:
    """Encodes words by a sentencepiece model with byte fallback."""

    def __init__(self, path: str):
        import sentencepiece

        self.model = sentencepiece.SentencePieceProcessor(model_file=path)
        self.fallback = np.array([self.model.is_byte(i) for i in range(self.model.get_piece_size())])

    def encode(self, words: list[str]) -> list[list[int]]:
        return self.model.encode(words, num_threads=1)


class RankVocabulary:
    """Encodes words by a rank file; a token that is a part of one character counts as fallback."""

    def __init__(self, path: str, pattern: str):
        import base64

        import tiktoken

        with open(path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.model = tiktoken.Encoding("words", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
        self.fallback = np.zeros(max(ranks.values()) + 1, bool)
        for piece, i in ranks.items():
            try:
                piece.decode()
            except UnicodeDecodeError:
                self.fallback[i] = True

    def encode(self, words: list[str]) -> list[list[int]]:
        return self.model.encode_ordinary_batch([" " + w for w in words], num_threads=1)


def script_of(text: str) -> str:
    """The script of most letters among those seen first; a text of fewer letters than 1 in 50 has none."""
    best, most = "none", 0
    for name, found in _SCRIPTS:
        n = len(found.findall(text))
        if n > most:
            best, most = name, n
        if 2 * n > len(text):
            break
    if most == 0 and any(c.isalpha() for c in text):
        return "other"
    return best


def repeated_window_words(codes: np.ndarray, width: int = 8) -> int:
    """Positions in windows of ``width`` (a power of two) words that occur twice or more. Exact: windows are ranked pair by pair."""
    n = len(codes) - width + 1
    if n < 2:
        return 0
    ids, span = codes.astype(np.int64), 1
    while span < width:
        m = len(ids) - span
        pair = ids[:m] * (ids.max() + 1) + ids[span:]
        _, ids = np.unique(pair, return_inverse=True)
        span *= 2
        if ids.max() + 1 == len(ids):
            return 0
    hit = np.bincount(ids)[ids] > 1
    edge = np.zeros(len(codes) + 1, np.int64)
    edge[:n] += hit
    edge[width : width + n] -= hit
    return int((np.cumsum(edge[:-1]) > 0).sum())


def duplicate_lines(text: str) -> int:
    lines = [x for x in text.split("\n") if x.strip(SPACES)]
    return len(lines) - len(set(lines))


class Meter:
    """Measures the texts of one slice; keeps encoded words between slices."""

    def __init__(self, vocabulary):
        self.vocabulary = vocabulary
        self._empty()

    def _empty(self) -> None:
        self.code: dict[bytes, int] = {}
        self.starts, self.flat, self.n_fallback = np.zeros(1, np.int64), np.zeros(0, np.int32), np.zeros(0, np.int64)

    def _learn(self, words: list[bytes]) -> None:
        ids = self.vocabulary.encode([w.decode("utf-8", "replace") for w in words])
        lens = np.fromiter(map(len, ids), np.int64, len(ids))
        flat = np.fromiter((t for x in ids for t in x), np.int32, int(lens.sum()))
        at = np.concatenate([[0], np.cumsum(lens)])
        fb = np.concatenate([[0], np.cumsum(self.vocabulary.fallback[flat])])
        self.n_fallback = np.concatenate([self.n_fallback, fb[at[1:]] - fb[at[:-1]]])
        self.starts = np.concatenate([self.starts, self.starts[-1] + at[1:]])
        self.flat = np.concatenate([self.flat, flat])

    def __call__(self, texts: list[str | None]) -> dict[str, list]:
        if len(self.code) > CACHE_WORDS:
            self._empty()
        docs, new, code = [], [], self.code
        for t in texts:
            words = (t or "").encode("utf-8", "surrogatepass").split()
            for w in set(words):
                if w not in code:
                    code[w] = len(code)
                    new.append(w)
            docs.append(np.fromiter(map(code.__getitem__, words), np.int64, len(words)))
        if new:
            self._learn(new)
        out: dict[str, list] = {f.split()[0]: [] for f in SCHEMA.split(", ")}
        for t, codes in zip(texts, docs):
            t = t or ""
            kinds, counts = np.unique(codes, return_counts=True)
            first, lens = self.starts[kinds], self.starts[kinds + 1] - self.starts[kinds]
            n_tokens = int((lens * counts).sum())
            chars = len(t) - sum(map(t.count, SPACES))
            row = (len(codes), chars, sum(map(t.count, SYMBOLS)), duplicate_lines(t), repeated_window_words(codes), n_tokens)
            share = float((self.n_fallback[kinds] * counts).sum()) / n_tokens if n_tokens else 0.0
            for k, v in zip(out, (*row, chars / n_tokens if n_tokens else 0.0, share, self._entropy(first, lens, counts, n_tokens), script_of(t))):
                out[k].append(v)
        return out

    def _entropy(self, first, lens, counts, n_tokens: int) -> float:
        if n_tokens == 0:
            return 0.0
        at = np.repeat(first - np.concatenate([[0], np.cumsum(lens)[:-1]]), lens) + np.arange(int(lens.sum()))
        tokens, weight = self.flat[at], np.repeat(counts, lens)
        order = np.argsort(tokens, kind="stable")
        tokens, weight = tokens[order], weight[order]
        n = np.add.reduceat(weight, np.flatnonzero(np.concatenate([[True], tokens[1:] != tokens[:-1]])))
        p = n / n_tokens
        return float(-(p * np.log2(p)).sum())


def measure(docs: DataFrame, vocabulary_path: str, *, id_col: str = "doc_id", text_col: str = "text", lang_col: str | None = None) -> DataFrame:
    """One row per document with the columns of ``SCHEMA``; ``lang`` too if ``lang_col`` is given."""
    cols = [F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")] + ([F.col(lang_col).alias("lang")] if lang_col else [])
    src = docs.select(*cols)
    extra = T._parse_datatype_string(SCHEMA)
    schema = T.StructType([src.schema["doc_id"], *([src.schema["lang"]] if lang_col else []), *extra.fields])

    def work():
        if vocabulary_path.endswith(".model"):
            meter = Meter(PieceVocabulary(vocabulary_path))
        else:
            import public_tokenizers

            meter = Meter(RankVocabulary(vocabulary_path, public_tokenizers.PATTERN))

        def act(batch: pa.RecordBatch) -> dict:
            out = meter(batch.column("text").to_pylist())
            out["doc_id"] = batch.column("doc_id")
            if lang_col:
                out["lang"] = batch.column("lang")
            return out

        return act

    return map_batches(src, work, schema)


def judge(measured: DataFrame, bands: dict[str, Band] | None = None, key: str = "script") -> DataFrame:
    """Adds base_failed and kept. ``bands`` by the values of ``key``; a value without a band has that of its script."""
    base = (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))

    def fits(b: Band):
        lo, hi = b.chars_per_token
        return F.col("chars_per_token").between(lo, hi) & (F.col("fallback_share") <= b.max_fallback) & ((F.col("n_tokens") < b.entropy_from) | (F.col("token_entropy") >= b.min_entropy))

    ok = F.lit(True)
    for s, b in SCRIPT_BANDS.items():
        ok = F.when(F.col("script") == s, fits(b)).otherwise(ok)
    for s, b in (bands or {}).items():
        ok = F.when(F.col(key) == s, fits(b)).otherwise(ok)
    return measured.withColumn("base_failed", base).withColumn("kept", ~base & ok)


def length_class(n_tokens: Column) -> Column:
    """Powers of four of the token count from 64 to 4096: the spread of characters per token and the entropy depend on it."""
    return F.greatest(F.lit(3), F.least(F.lit(6), F.floor(F.log2(F.greatest(n_tokens, F.lit(1))) / 2))).cast("int")


def fit_bands(measured: DataFrame, key: str = "lang", spread: float = 3.0, tail: float = 0.05, least: int = 1) -> dict[str, Band]:
    """Bands by the values of ``key`` from quantiles of all documents: medians plus or minus so many times the distance to the ``tail`` points at either side. A value of fewer than ``least`` documents gets none. As many rows reach the driver as there are values."""
    q = lambda c: F.percentile_approx(c, [tail, 0.5, 1 - tail], 1000)
    entropy = F.when(F.col("n_tokens") >= Band.entropy_from, F.col("token_entropy"))
    found = measured.filter((F.col("n_words") >= 20) & F.col(key).isNotNull()).groupBy(key).agg(q("chars_per_token").alias("c"), q("fallback_share").alias("f"), q(entropy).alias("e"), F.count(F.lit(1)).alias("n"))
    rows = found.filter(F.col("n") >= least).collect()
    return {r[key]: Band((r.c[1] - spread * (r.c[1] - r.c[0]), r.c[1] + spread * (r.c[2] - r.c[1])), r.f[1] + spread * max(r.f[2] - r.f[1], 0.01), max(0.0, r.e[1] - spread * (r.e[1] - r.e[0])) if r.e else 0.0) for r in rows}


def judge_fitted(measured: DataFrame, spread: float = 4.0, least: int = 30) -> DataFrame:
    """Judged by bands that all documents passing the base rule give, by language and length class. Quartiles carry the width: up to a quarter of bad documents at a side leave it as it is. Documents without such a band are judged by script. Measured rows must have ``lang``."""
    rows = written(measured.withColumn("band", F.concat("lang", F.lit("/"), length_class(F.col("n_tokens")))), "fertility")
    return judge(rows, fit_bands(judge(rows).filter(~F.col("base_failed")), "band", spread, 0.25, least), "band")
