"""From raw documents to packed training sequences: five operators in a row, each stage written and read again.

Quality rules, exact duplicates, near duplicates and mixing return the columns of documents; packing, the last, returns
one row per piece of a sequence. A stage works on all that the one before it kept.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from recall_engine.llm import encoding, exact_dedup, host_rules, mixing, packing, parity_join
from recall_engine.llm.scratch import fresh_path


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the host rules keep."""
    return host_rules.kept_documents(docs)


def without_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the document with the largest doc_id."""
    return exact_dedup.keep_one(docs)


def without_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies the document with the smallest doc_id."""
    return parity_join.one_of_each(docs)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row for each reading of a document that the mix takes; one that it reads twice is there twice."""
    return mixing.mixed_documents(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of at most 2048 tokens and their places in sequences."""
    return packing.packed(docs, encoding.default_tokenizer("word_bpe_49k.json"), end_id=0, capacity=2048)


STAGES = [("quality rules", quality), ("exact dedup", without_copies), ("n-gram Jaccard join", without_near_copies), ("mixing", mix), ("best-fit packing", pack)]

#: Tokenizers and the connected components have no SQL form; the stages are tested against brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for number, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if number < len(STAGES) - 1:
            path = fresh_path(spark, f"stage-{number}")
            docs.write.parquet(path)
            docs = spark.read.parquet(path)
    return docs
