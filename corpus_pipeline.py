"""A corpus pipeline of five stages over the ``documents`` table.

Each stage is (name, function); a function takes (spark, docs, sf_dir) and returns a
DataFrame. ``run`` writes each stage's rows to the shared folder and gives them to the
next, so a lost executor costs one stage at most.

Defined cases, in every stage: an empty table gives an empty one; other columns go through
unchanged, whatever their names; repeated rows are judged each (near-duplicates: rows of one
id are one document); a null text has no words, lines or windows and is scored, compared and
encoded as an empty one (line dedup leaves it null); a row with a null id is scored and
decontaminated like any, and kept by line dedup and near-dedup.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from fieldpress.llm import bpe, contamination, lines, quality, queries, simhash
from fieldpress.llm.common import table, written


def good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier does not reject (score of 0.7 or more)."""
    return quality.keep_good(docs, queries.quality_machine(spark, docs, sf_dir), 0.7)


def unrepeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with later occurrences of repeated three-line windows cut out."""
    return lines.remove_repeats(docs)


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of the smallest id of each near-duplicate group."""
    return simhash.keep_one(docs)


def uncontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no more of the benchmark than the rule allows."""
    return contamination.drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, token ids and their digests."""
    import public_tokenizers

    return bpe.encode(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


STAGES = [
    ("factorisation_quality", good_quality),
    ("line_dedup", unrepeated_lines),
    ("simhash_near_dedup", one_of_each),
    ("benchmark_decontamination", uncontaminated),
    ("byte_bpe", encoded),
]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs
