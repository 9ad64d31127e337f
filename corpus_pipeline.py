"""From raw documents to token digests in five stages; each is written as Parquet and read again as the next one's input."""
from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from flowblocks.llm import bpe_codec, decontaminate, language_id, line_dedup, ngram_join
from flowblocks.llm.common import shared_folder, table
from flowblocks.llm.queries import vocabulary

MIN_SCORE = 0.5


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a letter, without text, or without a clear language go. Rows of one doc_id go together, where the
    text of any of them is rejected; rows without doc_id stay."""
    gone = language_id.identify(docs).where((F.col("lang_pred") == "und") | (F.col("score") < MIN_SCORE)).select("doc_id")
    return docs.join(gone.distinct(), "doc_id", "left_anti").select(docs.columns)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Recurring lines go; a document of which nothing is left goes with them."""
    out = line_dedup.dedup(docs, long_words=line_dedup.LONG)
    out = out.where((F.col("n_dropped") == 0) | (F.trim("text") != ""))
    return out.withColumn("n_chars", F.length("text").cast("bigint")).select(docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class stays, the one with the smallest doc_id; five words and 0.8. Rows without doc_id stay."""
    gone = ngram_join.classes(docs, n=5, num=80, den=100).where("doc_id <> component_id").select("doc_id")
    return docs.join(gone.distinct(), "doc_id", "left_anti").select(docs.columns)


def decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark"))


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return bpe_codec.encode_documents(docs, vocabulary("word_bpe_49k.json"), digests_only=True)


STAGES = [("language_id", language), ("line_dedup", lines), ("ngram_join", near_duplicates), ("decontamination", decontaminated), ("bpe_codec", tokens)]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; what a stage returns is kept in the shared checkpoint folder."""
    root = f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    docs = table(spark, sf_dir, "documents")
    for i, (name, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{root}/{i}-{name}")
        docs = spark.read.parquet(f"{root}/{i}-{name}")
    return docs
