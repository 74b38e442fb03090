"""Five stages over documents: toxicity, quality rules, n-gram join, paragraph removal, packing.

Each stage gets the table that the one before wrote. All but the last return the columns of
documents; the last returns the places of the kept documents' pieces in packed sequences.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from gridchain.llm.ngram_join import keep_one
from gridchain.llm.packing import pack_documents
from gridchain.llm.paragraphs import drop_repeats
from gridchain.llm.rules import keep_ruled
from gridchain.llm.shared import stage
from gridchain.llm.toxicity import keep_harmless


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity score stays below the threshold."""
    return keep_harmless(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the base rules and the limits of their language and source."""
    return keep_ruled(docs)


def ngram_join(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of smallest doc_id of each group of near copies."""
    return keep_one(docs)


def substring_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without paragraphs and passages that an earlier document holds."""
    return drop_repeats(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Places of all pieces in sequences of 4096 tokens."""
    import public_tokenizers

    return pack_documents(docs, str(public_tokenizers.path("word_bpe_49k.json")))


STAGES = [("toxicity", toxicity), ("quality_rules", quality_rules), ("ngram_join", ngram_join), ("substring_dedup", substring_dedup), ("packing", packing)]

#: Learned scores and similarity components have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written as Parquet and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, function in STAGES:
        docs = stage(function(spark, docs, sf_dir), name)
    return docs
