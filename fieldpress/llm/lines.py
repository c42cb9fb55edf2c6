"""Line deduplication over overlapping three-line windows.

A text is cut into lines. Lines end at line breaks and, with ``prose`` (the default), also
after sentences and inside long sentences, as passages often stand in one long line: at
word ``LEAST`` to ``MOST``, if there after a comma or the like, else after the first word
that ends in one of the rarer letters of ``ENDS``, else of the next, and so on. So the cuts
follow the words themselves and fall alike in every copy of a passage (in Latin letters;
other scripts are cut at punctuation and after ``MOST`` words). Every window of
three consecutive lines is hashed; windows found more than once are looked up globally,
each later occurrence covers its three lines, and covered lines go. Text that stays is
kept byte for byte.

DataFrame functions only. Windows (two hashes, id, position) are written once; hashes are
counted with partial aggregation, then joined with the repeated ones (a shuffled join whose
hot keys AQE can split). The covered ranges are broadcast up to ``BROADCAST_BYTES``, else
joined by a shuffle.

Defined cases: null text stays null; fewer than three lines: no window, nothing removed; a
text all of whose lines are covered becomes empty; rows with a null id are neither indexed
nor changed; rows that share an id and a text are one document; every window with a
non-empty line counts, however short (spaces at line ends not counted); ids may be of any
ordered type; the first occurrence is that of the smallest id, then position.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import unused, written

#: Largest broadcast of covered ranges, in bytes.
BROADCAST_BYTES = 32_000_000
#: Position 10^9 a document: integral ids and positions are packed in one decimal for the minimum.
_POSITIONS = 1_000_000_000
#: Words of a line that may be cut, and of the longest line.
LEAST, MOST = 5, 12
#: Last letters of a word after which a long sentence is cut: rare ones first.
ENDS = ("pxfk", "dh", "tl")


def _prose(java: bool) -> str:
    """A line as a pattern. Alternatives in order: an end within fewer than LEAST words; punctuation; a word of each group of ENDS; MOST words; the rest. For Java words are taken whole (possessively) and ends are looked for behind; the other form needs neither and matches the same."""
    word, few, more = ("[^ \n]*+" if java else "[^ \n]*"), f"{{0,{LEAST - 2}}}?", f"{{{LEAST - 1},{MOST - 1}}}?"
    after = lambda x: f"{word}(?<=[{x}]) " if java else f"{word}[{x}] "
    end = lambda x: f"{word}(?:\n|(?<=[{x}]) )" if java else f"{word}(?:\n|[{x}] )"
    marks = [f"(?:{word} ){more}{end('.!?,;:')}", *[f"(?:{word} ){more}{after(x)}" for x in ENDS]]
    return "|".join([f"(?:{word} ){few}{end('.!?')}", *marks, f"(?:{word} ){{{MOST}}}", "[^\n]+"])


PROSE, PROSE_JAVA = _prose(False), _prose(True)
PLAIN = r"[^\n]*\n|[^\n]+"


def lines_of(text: Column, prose: bool = True) -> Column:
    """The lines with their separators; joined they are the text."""
    return F.regexp_extract_all(text, F.lit(PROSE_JAVA if prose else PLAIN), F.lit(0))


def windows(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", prose: bool = True) -> DataFrame:
    """id, tid (hash of the text), pos, and two hashes of each window of three lines."""
    hashed = F.transform(lines_of(F.col(text_col), prose), lambda x: F.xxhash64(F.btrim(x, F.lit(" \n"))))
    src = docs.filter(F.col(id_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(id_col).alias("id"), F.hash(text_col).alias("tid"), hashed.alias("a"))
    out = src.filter(F.size("a") >= 3).select("id", "tid", "a", F.explode(F.sequence(F.lit(0), F.size("a") - 3)).alias("pos"))
    out = out.select("id", "tid", "pos", *[F.col("a")[F.col("pos") + i].alias(f"h{i}") for i in range(3)])
    empty = F.xxhash64(F.lit(""))
    full = out.filter((F.col("h0") != empty) | (F.col("h1") != empty) | (F.col("h2") != empty))
    return full.select("id", "tid", "pos", F.xxhash64("h0", "h1", "h2").alias("k1"), F.hash("h0", "h1", "h2").alias("k2"))


def covered(docs: DataFrame, **kw) -> DataFrame:
    """id, tid, covered (merged ranges of lines to remove)."""
    found = written(windows(docs, **kw), "line-windows")
    place: Column = F.struct("id", "pos")
    if isinstance(found.schema["id"].dataType, T.IntegralType):  # a number can be combined in place, before the shuffle
        place = (F.col("id").cast("decimal(19,0)") * F.lit(_POSITIONS).cast("decimal(10,0)") + F.col("pos").cast("decimal(10,0)")).cast("decimal(31,0)")
    repeated = found.groupBy("k1", "k2").agg(F.count(F.lit(1)).alias("n"), F.min(place).alias("first")).filter(F.col("n") > 1).select("k1", "k2", "first")
    repeated = written(repeated, "repeated-windows")
    later = found.join(repeated, ["k1", "k2"]).filter(place > F.col("first"))
    starts = later.groupBy("id", "tid").agg(F.array_sort(F.collect_set("pos")).alias("s"))
    return written(starts.select("id", "tid", merged(F.col("s")).alias("covered")), "covered-lines")


def merged(s: Column) -> Column:
    """Ranges [a, b) of lines covered by windows at the sorted starts; windows that meet or overlap are one range."""
    first = F.filter(s, lambda x, i: (i == 0) | (x - F.element_at(s, F.greatest(i, F.lit(1))) > 3))
    last = F.filter(s, lambda x, i: (i == F.size(s) - 1) | (F.element_at(s, F.least(i + 2, F.size(s))) - x > 3))
    return F.zip_with(first, last, lambda a, z: F.struct(a.alias("a"), (z + 3).alias("b")))


def remove_repeats(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", prose: bool = True, counts: tuple[str, str] | None = None, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """docs with the later occurrences of repeated windows cut from the text; every row stays. ``counts`` names two more columns: lines and removed lines."""
    gone = covered(docs, id_col=id_col, text_col=text_col, prose=prose)
    tid, key, ids, cov = unused(docs, "tid", "gone_tid", "gone_id", "covered")
    gone = gone.select(F.col("id").alias(ids), F.col("tid").alias(key), F.col("covered").alias(cov))
    # a row in memory: two numbers and a header, and 32 bytes for each range
    size = gone.agg(F.sum(F.lit(64) + F.coalesce(F.octet_length(F.col(ids).cast("string")), F.lit(0)) + 32 * F.size(cov))).first()[0] or 0
    both = docs.withColumn(tid, F.hash(text_col)).join(F.broadcast(gone) if size <= broadcast_bytes else gone.hint("merge"), (F.col(id_col) == F.col(ids)) & (F.col(tid) == F.col(key)), "left")
    (out,) = unused(both, "out")

    def kept(a: Column) -> Column:  # a is bound by a lambda, and so are its marks: other expressions are evaluated for each element
        some = F.transform(F.array(_marks(F.col(cov), F.size(a))), lambda gone: F.filter(a, lambda x, i: ~F.element_at(gone, i + 1)))
        return F.array_join(F.element_at(some, 1), "")

    def row(a: Column) -> Column:
        return F.struct(F.size(a).alias("n"), F.when(F.col(cov).isNotNull(), kept(a)).alias("text"))

    touched = F.col(cov).isNotNull() if counts is None else F.lit(True)  # lines are cut once a row, and only where they are asked for
    found = F.when(touched, F.element_at(F.transform(F.array(lines_of(F.col(text_col), prose)), row), 1))
    made = both.withColumn(out, found)
    text = F.when(F.col(cov).isNull(), F.col(text_col)).otherwise(F.col(f"{out}.text"))
    if counts is None:
        return made.withColumn(text_col, text).select(*docs.columns)
    n_gone = F.coalesce(F.aggregate(cov, F.lit(0), lambda n, r: n + r["b"] - r["a"]), F.lit(0))
    n_lines = F.when(F.col(text_col).isNull(), F.lit(0)).otherwise(F.col(f"{out}.n"))
    return made.withColumns({counts[0]: n_lines.cast("long"), counts[1]: n_gone.cast("long"), text_col: text}).select(*docs.columns, *counts)


def _marks(ranges: Column, n: Column) -> Column:
    """An array of n booleans, true within the ranges; linear in n."""
    ends = F.concat(F.array(F.lit(0)), F.transform(ranges, lambda r: r["b"]))
    all_ = F.concat(ranges, F.array(F.struct(n.cast("int").alias("a"), n.cast("int").alias("b"))))
    return F.flatten(F.zip_with(ends, all_, lambda p, r: F.concat(F.array_repeat(F.lit(False), r["a"] - p), F.array_repeat(F.lit(True), r["b"] - r["a"]))))


def sql(prose: bool = True) -> str:
    """The same result in DuckDB: lines and windows as strings, for one row per id."""
    pattern = (PROSE if prose else PLAIN).replace("'", "''")
    return rf"""
WITH cut AS (
  SELECT doc_id, text, regexp_extract_all(text, '{pattern}') AS a FROM documents
), line AS (
  SELECT doc_id, unnest(a) AS s, unnest(range(len(a)))::BIGINT AS pos FROM cut
), win AS (
  SELECT doc_id, pos, trim(s, ' ' || chr(10)) AS x,
    lead(trim(s, ' ' || chr(10)), 1) OVER w AS y, lead(trim(s, ' ' || chr(10)), 2) OVER w AS z
  FROM line WINDOW w AS (PARTITION BY doc_id ORDER BY pos)
), seen AS (
  SELECT doc_id, pos, row_number() OVER (PARTITION BY x, y, z ORDER BY doc_id, pos) AS r
  FROM win WHERE z IS NOT NULL AND (x <> '' OR y <> '' OR z <> '')
), gone AS (
  SELECT DISTINCT doc_id, pos + o.k AS pos FROM seen, (SELECT unnest([0, 1, 2]) AS k) o WHERE r > 1
), kept AS (
  SELECT l.doc_id, count(*) AS n_lines, count(g.pos) AS n_removed,
    coalesce(string_agg(l.s, '' ORDER BY l.pos) FILTER (WHERE g.pos IS NULL), '') AS t
  FROM line l LEFT JOIN gone g ON l.doc_id = g.doc_id AND l.pos = g.pos GROUP BY l.doc_id
)
SELECT d.doc_id, coalesce(k.n_lines, 0)::BIGINT AS n_lines, coalesce(k.n_removed, 0)::BIGINT AS n_removed,
  CASE WHEN d.text IS NOT NULL THEN sha256(coalesce(k.t, '')) END AS text_sha256 FROM documents d LEFT JOIN kept k ON d.doc_id = k.doc_id
"""
