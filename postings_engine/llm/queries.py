"""The contract's queries: thin layers over the operators of this subpackage."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe_codec, embedding_dedup, license_scan, mixing, ngram_join, quality_rules, secret_scan, token_counts, toxicity, url_filters
from .common import read


def op1_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filters.judge_urls(read(spark, sf_dir, "pages"), url_filters.rule_table(spark))


def op2_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.similar_groups(read(spark, sf_dir, "documents"), 3, 90)


def op3_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.secret_digest(read(spark, sf_dir, "documents"))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels")
    fold = lambda c: F.crc32(F.col(c).cast("string").cast("binary")) % 5
    lexicon = toxicity.learn(docs, labels.where(fold("doc_id") != 0))
    out = toxicity.score(docs, lexicon)
    return out.select("doc_id", F.coalesce(fold("doc_id") == 0, F.lit(False)).alias("held_out"), "score", "predicted")


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(read(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op6_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_codec.roundtrip_digest(read(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.tiktoken"))


def op7_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The contract's columns, and ``spans``: label:first word:last word:edits of each bounded-error match."""
    out = license_scan.scan_licenses(read(spark, sf_dir, "documents"))
    spans = F.transform("matches", lambda m: F.concat_ws(":", m["label"], m["first"].cast("string"), m["last"].cast("string"), m["edits"].cast("string")))
    return out.withColumn("spans", F.array_join(spans, ",")).drop("matches")


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(read(spark, sf_dir, "documents")).drop("copies")


def op9_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.judge(read(spark, sf_dir, "documents"))


def op10_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embedding_dedup.near_duplicates(read(spark, sf_dir, "embeddings"))


QUERIES = {f.__name__: f for f in (op1_url_filters, op2_ngram_jaccard_join, op3_secret_scan, op4_toxicity, op5_token_counts, op6_byte_bpe, op7_license_scan, op8_mixing, op9_quality_rules, op10_embedding_near_dedup)}
ORACLE_SQL = {"op1_url_filters": url_filters.ORACLE, "op9_quality_rules": quality_rules.ORACLE}
