"""Byte-level BPE encoding and decoding by ranked merges.

The pattern cuts a text into pieces; every distinct piece of a slice is merged once over
its byte array: while some neighbouring pair is in the rank map, all occurrences of the
lowest-ranked pair join. Decoding concatenates the binary pieces of the ids.

``fold_words`` is the same fold in Spark's higher-order functions over a column of words,
with the rank map as one literal (buckets by hash, as a map literal alone is searched
linearly). ``encode`` runs the fold per Arrow batch: the higher-order form is interpreted
and takes hundreds of microseconds a word (figures in the README).

Row by row, no shuffle. Memory: a slice of texts and a cache of ``CACHE_WORDS`` words that
is emptied when full. A piece of over ``LONG`` bytes is merged with a heap, so that time
stays near-linear in its length.

Defined cases: a null text is encoded as the empty text (no ids); unpaired surrogates do
not occur in Spark strings; repeated rows give repeated results; other columns are not read.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from array import array

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import map_batches

CACHE_WORDS = 200_000
LONG = 128


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


def merge(word: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Ids of one piece: the fold of ranked merges over its bytes."""
    whole = ranks.get(word)
    if whole is not None:
        return [whole]
    if len(word) > LONG:
        return merge_long(word, ranks)
    parts = [word[i : i + 1] for i in range(len(word))]
    get = ranks.get
    pairs = [get(a + b) for a, b in zip(parts, parts[1:])]
    while True:
        low, at = None, -1
        for i, r in enumerate(pairs):
            if r is not None and (low is None or r < low):
                low, at = r, i
        if low is None:
            return [ranks[p] for p in parts]
        parts[at : at + 2] = [parts[at] + parts[at + 1]]
        del pairs[at]
        if at < len(pairs):
            pairs[at] = get(parts[at] + parts[at + 1])
        if at:
            pairs[at - 1] = get(parts[at - 1] + parts[at])


def merge_long(word: bytes, ranks: dict[bytes, int]) -> list[int]:
    """The same merges with a heap of (rank, position) over a linked list: n log n."""
    n = len(word)
    end = list(range(1, n + 1))  # end of the part that starts here, 0 once it has joined another
    before = list(range(-1, n - 1))
    heap = [(r, i, i + 2) for i in range(n - 1) if (r := ranks.get(word[i : i + 2])) is not None]
    heapq.heapify(heap)
    while heap:
        _, i, stop = heapq.heappop(heap)
        mid = end[i]
        if not mid or mid >= n or end[mid] != stop:
            continue
        end[i], end[mid] = stop, 0
        if stop < n:
            before[stop] = i
            if (r := ranks.get(word[i : end[stop]])) is not None:
                heapq.heappush(heap, (r, i, end[stop]))
        if (p := before[i]) >= 0 and (r := ranks.get(word[p:stop])) is not None:
            heapq.heappush(heap, (r, p, stop))
    out, i = [], 0
    while i < n:
        out.append(ranks[word[i : end[i]]])
        i = end[i]
    return out


class Words(dict):
    """Piece -> its ids as bytes of little-endian unsigned 32-bit integers, made on first use."""

    def __init__(self, ranks: dict[bytes, int]):
        super().__init__()
        self.ranks = ranks

    def __missing__(self, word: str) -> bytes:
        ids = array("I", merge(word.encode("utf-8", "replace"), self.ranks))
        got = self[word] = ids.tobytes()
        return got


class Coder:
    """Encodes texts and decodes ids; holds the pattern, the ranks and the cache of words."""

    def __init__(self, path: str, pattern: str):
        import regex

        self.find = regex.compile(pattern).findall
        self.ranks = read_ranks(path)
        self.pieces = [b""] * (max(self.ranks.values()) + 1)
        for piece, i in self.ranks.items():
            self.pieces[i] = piece
        self.words = Words(self.ranks)

    def encode(self, text: str | None) -> bytes:
        if len(self.words) > CACHE_WORDS:
            self.words.clear()
        return b"".join(map(self.words.__getitem__, self.find(text or "")))

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.pieces.__getitem__, memoryview(ids).cast("I")))


def encode(docs: DataFrame, path: str, pattern: str, *, id_col: str = "doc_id", text_col: str = "text", keep_ids: bool = True) -> DataFrame:
    """doc_id, n_tokens, token_ids (array of int, if keep_ids), ids_sha256, decoded_sha256, round_trip (the decoded bytes are the text's)."""
    src = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    fields = [src.schema["doc_id"], T.StructField("n_tokens", T.LongType())]
    fields += [T.StructField("token_ids", T.ArrayType(T.IntegerType()))] if keep_ids else []
    fields += [T.StructField("ids_sha256", T.StringType()), T.StructField("decoded_sha256", T.StringType()), T.StructField("round_trip", T.BooleanType())]

    def work():
        coder, sha = Coder(path, pattern), hashlib.sha256

        def act(batch: pa.RecordBatch) -> dict:
            texts = batch.column("text").to_pylist()
            ids = [coder.encode(t) for t in texts]
            back = [coder.decode(x) for x in ids]
            out = {
                "doc_id": batch.column("doc_id"),
                "n_tokens": [len(x) // 4 for x in ids],
                "ids_sha256": [sha(x).hexdigest() for x in ids],
                "decoded_sha256": [sha(x).hexdigest() for x in back],
                "round_trip": [b == (t or "").encode() for b, t in zip(back, texts)],
            }
            if keep_ids:
                out["token_ids"] = pa.ListArray.from_arrays(pa.array([0, *_running(len(x) // 4 for x in ids)], pa.int32()), pa.array(memoryview(b"".join(ids)).cast("I"), pa.int32()))
            return out

        return act

    return map_batches(src, work, T.StructType(fields))


def _running(sizes):
    total = 0
    for n in sizes:
        total += n
        yield total


def decode(encoded: DataFrame, path: str, *, id_col: str = "doc_id", ids_col: str = "token_ids") -> DataFrame:
    """doc_id and the decoded bytes of a column of ids (null: null)."""
    src = encoded.select(F.col(id_col).alias("doc_id"), F.col(ids_col).alias("ids"))
    schema = T.StructType([src.schema["doc_id"], T.StructField("decoded", T.BinaryType())])

    def work():
        pieces = {i: p for p, i in read_ranks(path).items()}

        def act(batch: pa.RecordBatch) -> dict:
            return {"doc_id": batch.column("doc_id"), "decoded": [None if x is None else b"".join(map(pieces.__getitem__, x)) for x in batch.column("ids").to_pylist()]}

        return act

    return map_batches(src, work, schema)


def rank_literal(ranks: dict[bytes, int], buckets: int = 4096) -> Column:
    """The rank map as one literal: an array of maps, in which a pair (as hex) is in the map of its CRC-32 modulo buckets."""
    import json
    import zlib

    parts: list[dict[str, int]] = [{} for _ in range(buckets)]
    for piece, r in ranks.items():
        parts[zlib.crc32(piece) % buckets][piece.hex().upper()] = r
    return F.from_json(F.lit(json.dumps(parts)), T.ArrayType(T.MapType(T.StringType(), T.IntegerType())))


def fold_words(word: Column, ranks: dict[bytes, int], buckets: int = 4096) -> Column:
    """Ids of a piece (string column) by Spark's higher-order functions alone: each step of the fold joins the pair of the lowest rank, first of equals first; bytes are hex strings."""
    table = rank_literal(ranks, buckets)
    none = F.lit(2**31 - 1)

    def rank(piece: Column) -> Column:
        return F.coalesce(F.element_at(F.element_at(table, (F.crc32(F.unhex(piece)) % buckets + 1).cast("int")), piece), none)

    def step(parts: Column, _: Column) -> Column:
        pairs = F.transform(F.sequence(F.lit(1), F.size(parts) - 1), lambda i: F.struct(rank(F.concat(F.element_at(parts, i), F.element_at(parts, i + 1))).alias("r"), i.alias("i")))
        joined = F.transform(
            F.array(F.array_min(pairs)),
            lambda best: F.when(
                best["r"] < none,
                F.concat(F.slice(parts, F.lit(1), best["i"] - 1), F.array(F.concat(F.element_at(parts, best["i"]), F.element_at(parts, best["i"] + 1))), F.slice(parts, best["i"] + 2, F.size(parts))),
            ).otherwise(parts),
        )
        return F.when(F.size(parts) < 2, parts).otherwise(F.element_at(joined, 1))

    hexed = F.hex(F.encode(word, "UTF-8"))
    n = F.octet_length(word)
    singles = F.when(n > 0, F.transform(F.sequence(F.lit(0), n - 1), lambda i: F.substring(hexed, i * 2 + 1, 2))).otherwise(F.array().cast("array<string>"))
    parts = F.aggregate(F.when(n > 1, F.sequence(F.lit(2), n)).otherwise(F.array().cast("array<int>")), singles, step)
    return F.transform(parts, rank)
