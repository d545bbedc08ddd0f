"""The corpus pipeline: every stage works on all that its predecessor kept.

Every stage takes any table with doc_id and text: other columns are carried whatever their names,
nulls in any column do no harm, and an empty table stays empty with its columns.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from deltamat.llm import common, decontaminate, lines, pieces, quality, simhash, wordsets
from deltamat.sources.scratch import materialize

#: No stage's decisions can be written in SQL (fitted vectors, MinHash, XXH64, WAND, a tokenizer).
ORACLE_SQL = None


def good_only(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier predicts 0 go; it learns from the table labels.

    Each row is judged by its whole text alone, so repeated rows go or stay together; a null or empty
    text goes by the share of label 1 in what was learned.
    """
    return quality.keep_good(docs, quality.fit(docs, common.table(spark, sf_dir, "labels")))


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of similar lines over all documents one stays; text and n_chars follow.

    A null text stays null, a document that loses all its lines stays with an empty text, and rows
    repeated with one doc_id and text are one document that gives the same result. Of lines that tie
    the one of the smallest doc_id (null first), then text hash, then line number stays.
    """
    return lines.dedup_lines(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each component one document stays, that of the smallest doc_id.

    Documents link at four differing bits of their fingerprints, and at Jaccard 0.8 of five-word shingles.
    Empty and null texts share one fingerprint and are one component. Equal ids with different texts
    are told apart; rows without doc_id stay only where their component has no id, one for each.
    """
    return simhash.drop_near_duplicates(docs, words=wordsets.SETTINGS)


def clean_of_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a test item go; null and empty texts stay, repeated rows go or stay together."""
    return decontaminate.drop_contaminated(docs, common.table(spark, sf_dir, "benchmark"))


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document that is left, a row for each row; null and empty texts have none."""
    return pieces.encode(docs)


STAGES = [
    ("quality_classifier", good_only),
    ("line_dedup", line_dedup),
    ("simhash_near_dedup", near_dedup),
    ("benchmark_decontamination", clean_of_benchmark),
    ("sentencepiece", tokens),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages over the whole documents table, each written as Parquet and read again."""
    docs = common.table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
