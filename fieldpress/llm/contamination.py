"""Benchmark decontamination by a prefix-filtered set join.

An item's windows are 13 consecutive words (a shorter item is one window). A window's words
are ordered by rarity over the whole corpus; containing the window needs every word, so
its rarest word is a sufficient prefix. Document words that are some window's prefix are
candidates; bounds on length and position prune them, and the window's words are compared
with the document's exactly.

DataFrame functions only. The corpus is read twice (counts of benchmark words, then the
join). Tables that come from the benchmark are broadcast up to ``BROADCAST_BYTES``; a larger
one is joined by a shuffle of the document words that are some window's prefix, each with
its neighbourhood, in the same one pass. Only matches and one row a document are shuffled
otherwise, by document.

Rows are told apart by their place in the scan of ``docs``, which must be a table (files
are read in the same splits each time, also when a task is repeated).

Defined cases: null text has no words; an item without words has no window; equal items
count each; equal rarity is ordered by word; repeated rows and rows with a null id are
judged each and each has its result; an empty benchmark gives no hits; ids may be of any type.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import unused, written

WINDOW = 13
#: Broadcast up to so many bytes (of words and arrays as they stand in memory, estimated).
BROADCAST_BYTES = 64_000_000
WORD_BYTES = 48
#: Buckets that tell which document words can be a prefix of a window; as longs some 16 MB in a broadcast.
_BUCKETS = 1 << 20
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_GAPS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def words_of(text: Column) -> Column:
    """Words after lower-casing A-Z only; texts of ASCII alone take the faster way."""
    low = F.when(F.octet_length(text) == F.length(text), F.lower(text)).otherwise(F.translate(text, _UPPER, _LOWER))
    return F.filter(F.split(F.coalesce(low, F.lit("")), _GAPS, -1), lambda w: w != "")


def item_windows(items: DataFrame, *, item_col: str = "item_id", text_col: str = "text", size: int = WINDOW) -> DataFrame:
    """w (the words of a distinct window) and items (the ids that have it)."""
    src = items.select(F.col(item_col).cast("string").alias("item"), words_of(F.col(text_col)).alias("words")).filter(F.size("words") > 0)
    at = F.explode(F.sequence(F.lit(1), F.greatest(F.size("words") - size + 1, F.lit(1))))
    return src.select("item", "words", at.alias("i")).select("item", F.slice("words", F.col("i"), size).alias("w")).groupBy("w").agg(F.collect_set("item").alias("items"))


def rarity(docs: DataFrame, vocabulary: DataFrame, few: bool, *, text_col: str = "text") -> DataFrame:
    """word, n: how often each word of the vocabulary (column word) occurs in all documents."""
    words = docs.select(F.explode(words_of(F.col(text_col))).alias("word"))
    found = words.join(F.broadcast(vocabulary) if few else vocabulary, "word", "left_semi").groupBy("word").agg(F.count(F.lit(1)).alias("n"))
    return vocabulary.join(F.broadcast(found) if few else found, "word", "left").select("word", F.coalesce("n", F.lit(0)).alias("n"))


def prefixes(windows: DataFrame, counts: DataFrame, few: bool) -> DataFrame:
    """token (the rarest word), off (its first place in the window), w, len, items. Common words stand in many windows: their counts are broadcast if few, else AQE splits the join."""
    place = windows.select("w", "items", F.posexplode("w").alias("off", "word")).join(F.broadcast(counts) if few else counts, "word")
    first = place.groupBy("w").agg(F.first("items").alias("items"), F.min(F.struct("n", "word", "off")).alias("p"))
    return first.select(F.col("p.word").alias("token"), F.col("p.off").alias("off"), "w", F.size("w").alias("len"), "items")


def occurrences(docs: DataFrame, table: DataFrame, few: bool, *, text_col: str = "text", size: int = WINDOW) -> DataFrame:
    """rid, n_words, start, len, items for each exact occurrence, and one row without start for each row of docs (``id`` goes through)."""
    src = docs.select("rid", "id", words_of(F.col(text_col)).alias("words"))
    src = src.select("rid", "id", "words", F.size("words").cast("long").alias("n_words"))
    start = F.col("p") - F.col("off")
    inside = (start >= 1) & (start + F.col("len") - 1 <= F.col("n_words"))
    none = F.lit(None)
    if few:
        marker = docs.sparkSession.range(1).select(F.lit("").alias("token"), F.lit(0).alias("off"), none.cast("array<string>").alias("w"), F.lit(0).alias("len"), none.cast("array<string>").alias("items"))
        spread = src.select("*", F.posexplode(F.concat(F.array(F.lit("")), F.col("words"))).alias("p", "token"))
        same = F.slice("words", F.when(inside, start).otherwise(F.lit(1)), F.col("len")) == F.col("w")
        hit = spread.join(F.broadcast(table.select("token", "off", "w", "len", "items").union(marker)), "token").filter(F.col("w").isNull() | (inside & same))
        return hit.select("rid", "id", "n_words", F.when(F.col("w").isNotNull(), start).alias("start"), "len", "items")
    # words that may be a prefix only (told by a bounded table of hash buckets), each with the words around it
    bucket = lambda c: F.pmod(F.xxhash64(c), F.lit(_BUCKETS)).alias("bucket")
    first = F.greatest(F.col("p") - (size - 1), F.lit(1))
    spread = src.select("rid", "id", "n_words", "words", F.posexplode("words").alias("p0", "token")).select("rid", "id", "n_words", "words", (F.col("p0") + 1).alias("p"), "token", bucket("token"))
    spread = spread.join(F.broadcast(table.select(bucket("token")).distinct()), "bucket", "left_semi")
    spread = spread.select("rid", "id", "n_words", "p", "token", F.slice("words", first, F.lit(2 * size - 1)).alias("near"), first.alias("from"))
    same = F.slice("near", F.when(inside, start - F.col("from") + 1).otherwise(F.lit(1)), F.col("len")) == F.col("w")
    hit = spread.join(table, "token").filter(inside & same).select("rid", "id", "n_words", start.alias("start"), "len", "items")
    return hit.union(src.select("rid", "id", "n_words", none.cast("int"), F.lit(0), none.cast("array<string>")))


def contaminated(docs: DataFrame, items: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", size: int = WINDOW, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items (sorted ids as strings), contaminated, and t1, t2 (hashes of the text); one row for each row of docs."""
    windows = written(item_windows(items, item_col=item_col, text_col=item_text_col, size=size), "item-windows")
    vocabulary = written(windows.select(F.explode("w").alias("word")).distinct(), "item-words")
    few_words = vocabulary.count() * 2 * WORD_BYTES <= broadcast_bytes
    few_windows = windows.count() * (size + 4) * WORD_BYTES <= broadcast_bytes
    counts = written(rarity(docs, vocabulary, few_words, text_col=text_col), "word-counts")
    ranked = written(prefixes(windows, counts, few_words), "item-prefixes")
    src = docs.select(F.monotonically_increasing_id().alias("rid"), F.struct(F.col(id_col).alias("doc_id"), *_keys(text_col)).alias("id"), F.col(text_col).alias("text"))
    hits = occurrences(src, ranked, few_windows, size=size)
    # an occurrence becomes the positions it covers and its items; sets are combined before the shuffle
    span = F.struct("start", "len")
    one = hits.groupBy("rid").agg(F.first("id").alias("id"), F.max("n_words").alias("n_words"), F.collect_set(F.when(F.col("start").isNotNull(), span)).alias("spans"), F.collect_set("items").alias("items"))
    covered = F.size(F.array_distinct(F.flatten(F.transform("spans", lambda s: F.sequence(s["start"], s["start"] + s["len"] - 1)))))
    out = one.select("id.*", "n_words", F.when(F.size("spans") > 0, covered).otherwise(F.lit(0)).cast("long").alias("n_hit"), F.array_sort(F.array_distinct(F.flatten("items"))).alias("items"))
    return out.select("doc_id", "t1", "t2", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), "items", ((F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words"))).alias("contaminated"))


def _keys(text_col: str, names: tuple[str, str] = ("t1", "t2")) -> list[Column]:
    return [F.xxhash64(text_col).alias(names[0]), F.hash(text_col).alias(names[1])]


def drop_contaminated(docs: DataFrame, items: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", **kw) -> DataFrame:
    """docs without the contaminated rows, told by their text (96 bits of hashes): other rows of the same id stay, rows with a null id are judged like any."""
    from .common import without

    t1, t2 = unused(docs, "t1", "t2")
    found = contaminated(docs, items, id_col=id_col, text_col=text_col, **kw)
    gone = found.filter("contaminated").select(F.col("t1").alias(t1), F.col("t2").alias(t2))
    return without(docs.select("*", *_keys(text_col, (t1, t2))), gone, [t1, t2]).drop(t1, t2)


SQL = f"""
WITH dw AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+'), lambda x: x <> '') AS words FROM documents
), iw AS (
  SELECT item_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+'), lambda x: x <> '') AS words FROM benchmark
), w AS (
  SELECT item_id, array_to_string(words[i : least(i + {WINDOW - 1}, len(words))], ' ') AS g, least({WINDOW}, len(words)) AS n
  FROM iw, unnest(range(1, greatest(len(words) - {WINDOW - 2}, 2))) t(i) WHERE len(words) > 0
), sizes AS (SELECT DISTINCT n FROM w), d AS (
  SELECT doc_id, i, n, array_to_string(words[i : i + n - 1], ' ') AS g
  FROM dw, sizes, unnest(range(1, len(words) - n + 2)) t(i) WHERE len(words) >= n
), occ AS (SELECT d.doc_id, d.i, d.n, w.item_id FROM d JOIN w ON d.g = w.g AND d.n = w.n),
hit AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS p FROM occ) GROUP BY doc_id),
it AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS item FROM occ) GROUP BY doc_id)
SELECT dw.doc_id, len(words)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
  sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(words) AS contaminated
FROM dw LEFT JOIN hit ON dw.doc_id = hit.doc_id LEFT JOIN it ON dw.doc_id = it.doc_id
"""
