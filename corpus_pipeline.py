"""The corpus pipeline: quality, exact duplicates, near duplicates, secrets, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame that is written and read again as the next one's
docs. All stages but the last return the columns of documents. Null, empty and very long texts, null and repeated
ids, equal rows, empty tables and further columns of any name are taken by every stage; what becomes of them is told
by the operator that the stage calls.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from pointveil.llm import quality
from pointveil.llm.common import documents, labelled_sample, labels, staged
from pointveil.llm.exact_dedup import one_of_equals
from pointveil.llm.packing import pack
from pointveil.llm.secrets import mask
from pointveil.llm.simhash import one_of_each


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the neighbour vote rejects go."""
    voter = quality.train(labelled_sample(docs, labels(spark, sf_dir), "quality", 2, 4, quality.REFERENCES))
    return quality.keep_good(docs, voter)


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the row with the largest doc_id stays; of repeated equal rows one."""
    return one_of_equals(docs)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near duplicates (five words, exact Jaccard 0.8 or more) the row with the least doc_id stays."""
    return one_of_each(docs)


def secret_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Found secrets are replaced by their kind; n_chars follows."""
    return mask(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token-budget batches in optimal length buckets."""
    return pack(docs)


STAGES = [
    ("quality_classifier", quality_stage),
    ("exact_dedup", exact_stage),
    ("simhash_near_dedup", near_stage),
    ("secret_scans", secret_stage),
    ("packing", packing_stage),
]

#: The classifier's training and the length programme have no SQL form.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in order over documents, each result written and read again."""
    docs = documents(spark, sf_dir)
    for n, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if n < len(STAGES) - 1:
            docs = staged(docs)
    return docs
