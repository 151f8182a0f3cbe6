"""From raw documents to packed sequences: quality rules, near-duplicates, personal data, mix, packing.

Each stage takes (spark, docs, sf_dir) and works on all that the one before it kept; all but
the last return the columns of documents, and any further ones whatever their names.

Null and empty texts fail the quality rules; a null doc_id, lang or source is a value like any
other (null doc_ids come last in a group of copies, first in packing); very long texts are judged,
compared, redacted and packed whole; of tied documents that of the smallest doc_id stays; repeated
rows are one after the second stage; an empty table gives empty stages and no pieces.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from segdedup import scratch
from segdedup.llm import mixing, near_copies, packing, pii, quality_rules

WEIGHTS, SHARE = [3, 1, 2], 1.5


def good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules keep."""
    return quality_rules.accepted(scratch.spread(docs))


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near-duplicate texts (5-word Jaccard 0.8 or more, or op9's rule) one row, that
    of the smallest doc_id; of repeated rows one. Different texts of one doc_id, or of none, are apart."""
    return near_copies.one_of_each(docs)


def without_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts with personal data replaced; n_chars, where there is one, follows."""
    clean = pii.redact(docs)
    return clean.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in docs.columns else clean


def mixed_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it."""
    return mixing.rows(docs, WEIGHTS, SHARE)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of documents in sequences of 1024 ids."""
    import public_tokenizers

    return packing.pack(docs, public_tokenizers.path(packing.VOCABULARY))


STAGES = [
    ("quality rules", good_quality),
    ("near-duplicates", one_of_each),
    ("personal data", without_personal_data),
    ("source mix", mixed_sources),
    ("packing", packed),
]

#: SQL cannot express the stages; tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages applied to documents, each written and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = scratch.written(stage(spark, docs, sf_dir), f"pipeline-{name.replace(' ', '-')}")
    return docs
