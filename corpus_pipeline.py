"""From raw documents to token ids: quality rules, exact dedup, near-dedup, mixing, byte-level BPE.

Each stage takes (spark, docs, sf_dir) and works on all that the one before it kept; all but the last
return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from subwin.llm import bpe, exact_dedup, quality_rules, similar_dedup, simhash_dedup, source_mixing
from subwin.llm.common import table
from subwin.storage import Scratch

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that no quality rule rejects."""
    return quality_rules.filter_quality(docs, table(spark, sf_dir, "labels")).select(*COLUMNS)


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One of each group of equal texts."""
    return exact_dedup.drop_copies(docs).select(*COLUMNS)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One of each component of fingerprints that differ in two bits at most; of what is left, one of each component of
    texts whose five-word shingles are alike by 0.8 or more, which fingerprints mostly miss."""
    printed = Scratch(spark, "near").save(simhash_dedup.drop_near_copies(docs), "printed")
    return similar_dedup.drop_similar(printed).select(*COLUMNS)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it."""
    return source_mixing.mix(docs).select(*COLUMNS)


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of each row."""
    return bpe.encode_documents(docs, *bpe.public_vocabulary())


STAGES = [("quality_rules", quality), ("exact_dedup", exact), ("simhash_dedup", near), ("source_mixing", mixed), ("byte_bpe", encoded)]

#: Three stages aren't to be had in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scratch = Scratch(spark, "pipeline")
    for name, stage in STAGES[:-1]:
        docs = scratch.save(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
