"""Corpus pipeline: toxicity, MinHash near-dedup, benchmark decontamination, packing.

Each stage gets the documents that the one before it kept, as written and read again. All but the last return the
columns of documents; the last returns each kept document's place in a batch.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from prefix_credit.llm import decontaminate, near_dup, packing, toxicity
from prefix_credit.llm.common import staged, table


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the ordinal model, fitted on the labels, does not call toxic; null or empty texts stay."""
    return toxicity.without_toxic(docs, toxicity.fit(docs, table(spark, sf_dir, "labels")))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, the one with the smallest id, of each group of near-duplicates: five words a shingle, 0.8 or more alike.

    Rows repeated with their id are one document and stay as often as they came; of an id with several texts each is a
    document of its own; texts without words stay."""
    return near_dup.without_near_duplicates(docs, n=5, num=80, den=100)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    return decontaminate.without_contaminated(docs, table(spark, sf_dir, "benchmark"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every kept document with its length bucket, batch and place in it."""
    return packing.packed_documents(docs)


STAGES = [("toxicity", drop_toxic), ("near_dedup", drop_near_duplicates), ("decontamination", drop_contaminated), ("packing", pack)]

#: Fitted models and LSH tables have no SQL form; tests hold the pipeline against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents table, each written to the shared folder and read again."""
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = staged(docs)
    return docs
