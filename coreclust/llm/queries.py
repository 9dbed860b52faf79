"""The registered queries of the corpus operators: whole tables in, contract columns out."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, fixity, fmindex, kneserney, langid, minhash, packing, pii, rules, weak
from .common import Scratch, table
from .oracles import ORACLE_SQL


def doc_hash(modulus: int):
    """crc32 of doc_id as text, modulo; a null id counts as remainder -1."""
    return F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(modulus)), F.lit(-1))


def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fmindex.verdicts(fmindex.contaminated_spans(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))).drop("spans")


def op2_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.digests(pii.find(table(spark, sf_dir, "documents")))


def op3_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(table(spark, sf_dir, "documents"))


def op4_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"))


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.count_tokens(table(spark, sf_dir, "documents"))


def op6_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return weak.classify(table(spark, sf_dir, "documents"))


def op7_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scores, _ = kneserney.run(docs, ~doc_hash(7).isin(2, -1))
    return scores.withColumn("held_out", doc_hash(7) == 2)


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    profiles = langid.fit(docs.where(doc_hash(5) != 0))
    return langid.identify(docs, profiles).select("doc_id", (doc_hash(5) == 0).alias("held_out"), "lang_pred", "score")


def op9_warc_fixity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pages against a replica with stated damage: every 101st body altered, every 211th record lost."""
    pages = table(spark, sf_dir, "pages")
    replica = fixity.damaged(pages, {"flipped": F.col("page_id") % 101 == 13, "lost": F.col("page_id") % 211 == 5})
    return fixity.audit(pages, replica, Scratch(spark, "fixity"))


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    book = rules.ledger(rules.measure(table(spark, sf_dir, "documents")))
    book = rules.apply_policy(book, "v2", "kept")
    return book.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", (F.col("failed").bitwiseAND(F.lit(rules.mask("base"))) != 0).alias("base_failed"), "kept", "failed")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (op1_decontamination, op2_pii, op3_near_duplicates, op4_packing, op5_token_counts, op6_quality_classifier, op7_lm_scoring, op8_language_id, op9_warc_fixity, op10_quality_rules)
}

__all__ = ["ORACLE_SQL", "QUERIES"]
