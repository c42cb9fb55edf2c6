"""Registered queries of this subpackage and, where SQL can express them, their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import crc_bucket, table


def op1_fertility(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from . import fertility

    got = fertility.judge_fitted(fertility.measure(table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"), lang_col="lang"))
    return got.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "n_tokens", "chars_per_token", "fallback_share", "token_entropy", "script")


def op3_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from . import bpe

    return bpe.encode(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, keep_ids=False).select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "round_trip")


def op4_rank_order_langid(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import langid

    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    profiles = langid.learn(docs.filter(crc_bucket("doc_id", 5) != 0))
    return langid.identify(docs, profiles).select("doc_id", (crc_bucket("doc_id", 5) == 0).alias("held_out"), "lang_pred", "score")


#: Metadata that the quality score may use.
METADATA = ("n_chars",)


def quality_machine(spark: SparkSession, docs: DataFrame, sf_dir: str):
    from . import quality

    return quality.learn(docs, table(spark, sf_dir, "labels").filter(crc_bucket("doc_id", 4) != 2), metadata=METADATA)


def op6_factorisation_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import quality

    docs = table(spark, sf_dir, "documents")
    got = quality.score(docs, quality_machine(spark, docs, sf_dir))
    return got.select("doc_id", (crc_bucket("doc_id", 4) == 2).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


def op2_licence_dice(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import licences

    return licences.scan(table(spark, sf_dir, "documents"))


#: The rules that the contract of op5 fixes.
URL_RULES = [("allow", "com/"), ("block", "example.com/en/"), ("allow", "www.example.com/en/"), ("block", "net/es/"), ("block", "net/fr/")]


def op5_host_reputation(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import hosts

    pages = table(spark, sf_dir, "pages")
    got = hosts.judge(pages, hosts.count_outcomes(pages), URL_RULES)
    six = lambda c: F.floor(F.col(c) * 1e6 + 0.5) / 1e6
    return got.withColumns({"share": six("share"), "tail": six("tail")})


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import simhash

    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op8_weak_supervision_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import pii

    return pii.find(table(spark, sf_dir, "documents"))


def op9_line_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import lines

    out = lines.remove_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"), counts=("n_lines", "n_removed"))
    return out.select("doc_id", "n_lines", "n_removed", F.sha2("text", 256).alias("text_sha256"))


def op10_prefix_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import contamination

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    got = contamination.contaminated(docs, table(spark, sf_dir, "benchmark"))
    return got.select("doc_id", "n_words", "n_hit", "n_items", F.sha2(F.concat_ws(",", "items"), 256).alias("items_sha256"), "contaminated")


_ALL = (op1_fertility, op2_licence_dice, op3_byte_bpe, op4_rank_order_langid, op5_host_reputation, op6_factorisation_quality, op7_simhash, op8_weak_supervision_pii, op9_line_windows, op10_prefix_decontamination)
QUERIES = {f.__name__: f for f in _ALL}


def _sql() -> dict[str, str]:
    from . import contamination, hosts, licences, lines

    return {"op2_licence_dice": licences.sql(), "op5_host_reputation": hosts.sql(URL_RULES), "op9_line_windows": lines.sql(), "op10_prefix_decontamination": contamination.SQL}


SQL: dict[str, str] = _sql()
