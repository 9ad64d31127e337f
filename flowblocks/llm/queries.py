"""Thin queries over the operators, one for each, and the SQL that states the same where SQL can."""
from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe_codec, decontaminate, embedding_neardup, language_id, license_scan, line_dedup, ngram_join, pii, secret_scan, token_attribution
from .common import table, texts

ORACLES: dict[str, str] = {"op1_line_dedup": line_dedup.SQL}


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.report(texts(table(spark, sf_dir, "documents")))


def op2_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.report(texts(table(spark, sf_dir, "documents")))


def op3_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = secret_scan.find_secrets(texts(table(spark, sf_dir, "documents")))
    base = F.filter("findings", lambda x: x["kind"].isin("assign", "access", "hex"))
    n = lambda k: F.size(F.filter("findings", lambda x: x["kind"] == k)).cast("bigint").alias(f"n_{k}")
    return found.select("doc_id", n("assign"), n("access"), n("hex"), F.sha2(secret_scan.digest(base), 256).alias("base_sha256"), secret_scan.digest(F.col("findings")).alias("spans"))


def op4_embedding_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embedding_neardup.near_duplicates(table(spark, sf_dir, "embeddings"))


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.identify(table(spark, sf_dir, "documents"))


def op6_token_attribution(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return token_attribution.count_tokens(texts(table(spark, sf_dir, "documents")), vocabulary("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


def op7_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.report(texts(table(spark, sf_dir, "documents")), table(spark, sf_dir, "benchmark"))


def op8_bpe_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_codec.encode_documents(texts(table(spark, sf_dir, "documents")), vocabulary("word_bpe_49k.json"), digests_only=True)


def op9_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.classes(texts(table(spark, sf_dir, "documents")))


def op10_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.find_pii(texts(table(spark, sf_dir, "documents")))


QUERIES = {f.__name__: f for f in (op1_line_dedup, op2_license_scan, op3_secret_scan, op4_embedding_neardup, op5_language_id, op6_token_attribution, op7_decontaminate, op8_bpe_codec, op9_ngram_join, op10_pii)}
