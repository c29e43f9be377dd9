"""A corpus pipeline: quality, exact copies, near copies, source mix, packing. Each stage reads what the one before wrote."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tricount.llm import exact_dedup, mixing, near_dup, quality
from tricount.llm.common import Stages, table
from tricount.llm.queries import packed


def good_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.keep_good(docs, quality.train(docs, table(spark, sf_dir, "labels")))


def without_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return exact_dedup.drop_copies(docs)


def without_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near_dup.one_of_each(docs)


def mixed_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mixed(docs)


def packed_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packed(docs)


STAGES = [
    ("quality", good_documents),
    ("exact_dedup", without_exact_copies),
    ("ngram_jaccard", without_near_copies),
    ("mix_sources", mixed_sources),
    ("packing", packed_sequences),
]

#: The models and the near-copy components have no SQL form; tests/llm/test_pipeline.py holds each stage against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in order on the documents of `sf_dir`; what a stage keeps is written to the shared folder and read again, and removed when the next stage is written.

    Null and empty texts, repeated and null ids go through each stage as its operator states: a null id is never dropped as a copy, an empty text is scored like others and packed as its
    end mark alone. An empty table gives no rows. Further columns are carried to the last stage, which returns pieces.
    """
    stages = Stages(spark, "pipeline")
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES[:-1]):
        before, docs = docs, stages.write(stage(spark, docs, sf_dir))
        if k:
            stages.drop(before)
    return STAGES[-1][1](spark, docs, sf_dir)
