"""A training corpus from `documents`: quality rules, near-duplicate removal, secret masking, source mixing, encoding.

Each stage takes all that its predecessor kept and returns the columns of `documents`; the last adds `ids`.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from levelgrid.llm import jaccard_join, mixing, pieces, quality, secrets, token_count
from levelgrid.llm.common import settled, table


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rules or their language's reference reject go."""
    return quality.filtered_documents(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near copies stays, that with the smallest doc_id."""
    return jaccard_join.one_of_each(docs)


def secret_scan(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are masked; all documents stay."""
    return secrets.redacted_documents(docs)


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row for each time that the schedule takes a document, up to three times."""
    return mixing.mixed_documents(docs)


def encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents with their piece ids."""
    return pieces.encode_documents(docs, token_count.vocabulary_path("piece_bpe_32k.model"))


STAGES = [
    ("quality_rules", quality_rules),
    ("near_duplicates", near_duplicates),
    ("secret_scan", secret_scan),
    ("source_mix", source_mix),
    ("encoding", encoding),
]

#: gram joins, the forest and the encoder are not SQL; tests/llm hold run() against a brute-force version
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the whole table; each stage's rows are kept in reliable storage for the next one, which reads them more than once."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = settled(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
