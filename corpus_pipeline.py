"""Corpus pipeline over ``documents``: quality classifier, line dedup, n-gram Jaccard join, benchmark
decontamination, mixing to target weights. Each stage is written as Parquet and reread as the next
one's input; all return the columns of documents, others that the input has among them.

Defined results: a null or empty text has no words and no lines, passes all stages but the draw, and there
has its cell's probability (a document that loses all its lines to the second stage goes, one that had
none does not); null source or lang are categories of their own; rows without a doc_id are never near
duplicates and share one draw; of rows that repeat a doc_id the third stage keeps
one; texts of any length are read whole; extra columns of any name are carried along; without labels
or without a benchmark the stages that use them keep everything; an empty table gives no rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from evigraph.llm import decontamination, jaccard_join, line_dedup, mixing, quality
from evigraph.llm.common import table, written


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents judged junk or toxic go."""
    return quality.good(docs, table(spark, sf_dir, "labels"))


def line_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that repeat an earlier line, exactly or within two edits, go."""
    return line_dedup.without_repeats(docs)


def ngram_jaccard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents with like shingle sets, the one of the smallest id stays."""
    return jaccard_join.one_of_each(docs)


def benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with too large a share of benchmark passages go."""
    return decontamination.decontaminated(docs, table(spark, sf_dir, "benchmark"))


def mixing_weights(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A sample whose tokens meet the target shares of sources, languages and topics."""
    return mixing.sampled(docs)


STAGES = [
    ("quality classifier", quality_classifier),
    ("line dedup", line_repeats),
    ("n-gram Jaccard join", ngram_jaccard),
    ("benchmark decontamination", benchmark),
    ("mixing sources to target weights", mixing_weights),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows that all stages keep."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir))
    return docs


#: Near-duplicate components and a trained classifier can't be told in SQL; tests hold the stages
#: against brute force.
ORACLE_SQL = None
