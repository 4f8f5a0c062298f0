"""The registered queries of this subpackage, each over its whole table, and their SQL where there is one."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import fingerprints, mixing, neardup, oracles, packing, pseudonyms, quality, resample, sharding, tokens, wrappers
from .common import written

#: For the registered queries only; a deployment passes a key of its own.
PSEUDONYM_KEY = "registered-query"


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.fingerprinted_documents(_table(spark, sf_dir, "documents"))


def op2_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(_table(spark, sf_dir, "documents"))


def op3_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(_table(spark, sf_dir, "documents"), tokens.tokenizer_path())


def op4_token_totals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Totals after four commits: all documents; the same batch again (changes nothing); toxic ones deleted; those of
    low quality revised to counts with an end id. Columns source, lang, tokenizer, n_docs, n_tokens."""
    docs, labels = _table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels")
    counts = written(tokens.token_counts(docs, tokens.tokenizer_path(), "word_bpe_49k"), "counts")
    toxic = labels.where("toxic = 1").select("doc_id").distinct()
    poor = labels.where("quality = 0").select("doc_id").distinct().join(toxic, "doc_id", "left_anti")
    old = counts.join(poor, "doc_id", "left_semi")
    new = old.withColumn("tokenizer", F.lit("word_bpe_49k+end")).withColumn("n_tokens", F.col("n_tokens") + 1)
    totals = tokens.TokenTotals(spark)
    totals.commit("1-load", tokens.inserts(counts))
    totals.commit("1-load", tokens.inserts(counts))
    totals.commit("2-toxic", tokens.deletes(counts.join(toxic, "doc_id", "left_semi")))
    totals.commit("3-revised", tokens.revisions(old, new))
    return totals.totals()


def op5_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    return pseudonyms.pseudonymised(docs, PSEUDONYM_KEY)


def op6_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.sharded_documents(_table(spark, sf_dir, "documents"))


def op7_wrappers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return wrappers.extracted_pages(_table(spark, sf_dir, "pages"))


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.judged_documents(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mixed_documents(_table(spark, sf_dir, "documents"))


def op10_resampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return resample.resampled_documents(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_fingerprints, op2_near_duplicates, op3_packing, op4_token_totals, op5_pseudonyms, op6_sharding, op7_wrappers, op8_quality, op9_mixing, op10_resampling)}


def oracle_sql() -> dict[str, str]:
    """For the others SQL lacks the hashes, tokenizers or parsers; tests hold them against brute force."""
    return oracles.oracle_sql()
