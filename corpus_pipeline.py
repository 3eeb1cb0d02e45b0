"""A corpus pipeline of five stages, each one operator of ``fieldtally.llm``.

Each stage is written as Parquet and read again as the next one's documents.  All but the
last return the columns of ``documents``; their decisions take effect: documents that the
quality classifier rejects go, one document of each near-copy group stays, personal data is masked
(and n_chars follows), and the mix keeps documents by their calibrated probabilities.  The
last stage returns ids and decoded bytes' digests of what is left.

Edge cases are those of the operators; an empty table passes through as an empty table.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fieldtally.llm import bpe_pieces, jaccard_join, pii_tagger, quality, raking
from fieldtally.llm.common import read_documents, scratch


def good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The classifier is fitted on labelled source documents; rejected documents go."""
    model = quality.train(read_documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return quality.keep_good(docs, model)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of the smallest id in each group of linked documents stays."""
    return jaccard_join.keep_first(docs)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every span of personal data gives way to its kind in angle brackets."""
    masked = pii_tagger.redact(docs)
    return masked.withColumn("n_chars", F.char_length("text").cast("long")) if "n_chars" in docs.columns else masked


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents sampled by probabilities raked to source, language and topic shares."""
    return raking.sample(docs)


def byte_pairs(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Digests of ids and decoded bytes."""
    return bpe_pieces.digest_documents(docs)


STAGES = [("quality classifier", good_quality), ("n-gram Jaccard join", near_duplicates), ("personal data", personal_data), ("mixing sources", source_mix), ("byte-level BPE", byte_pairs)]

#: SQL can express neither the classifier nor the tagger.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_documents(spark, sf_dir)
    for at, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if at < len(STAGES) - 1:
            docs = scratch(spark, docs, f"stage{at}")
    return docs
