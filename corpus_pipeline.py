"""A corpus pipeline of five operators: quality rules, near duplicates, personal data, mixing, encoding.

Every stage takes (spark, docs, sf_dir) and works on all that its predecessor
kept. All but the last return the columns of ``documents``; the last returns
the digests of the encoded texts. Nulls, empty texts, repeated rows, empty
tables and extra columns have the results that the operators define: rejected
documents go, one document of each near-duplicate group stays, personal data
are replaced, and documents are repeated as the mix asks.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from veil.llm import chunk_bpe, jaccard_join, pii_feistel, quality_ledger, systematic_mix
from veil.sources.shared import materialize, table


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality_ledger.keep(docs, "v1")


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return jaccard_join.keep_representatives(docs)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pii_feistel.pseudonymize(docs)


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return systematic_mix.sample(docs)


def encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return chunk_bpe.encode_documents(docs)


STAGES = [
    ("quality rules", quality),
    ("near duplicates", near_duplicates),
    ("personal data", personal_data),
    ("mixing", mixing),
    ("encoding", encoding),
]

#: SQL cannot express byte-pair encoding; tests compare each stage with a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; results between stages are written in the shared folder."""
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = materialize(docs, "stage-" + name.replace(" ", "-"))
    return docs
