"""The corpus pipeline: quality classifier, line dedup, one document of each near-copy group, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of documents.
Cases: null ids and texts, repeated rows and empty tables go through every stage as the operators' docstrings say.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from localcomm.llm import packing, quality, shingles, templates
from localcomm.llm.common import staged


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the ordinal classifier rejects go; it is fitted on the labels beside the documents."""
    ratings = quality.graded(spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return quality.selected(docs, quality.train(docs, ratings))


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines of recurring templates go but for their first document; documents left without words go too."""
    return templates.deduplicated(docs)


def near_copy_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents linked by five-word shingles at a similarity of 0.8 or more, the smallest id stays."""
    return shingles.kept_one(docs, shingles.JoinParams(words=5, percent=80))


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All that is left, packed into sequences of 2048 tokens: one row per piece.

    Passages shared by documents that are no near copies go first: before that stage they would leave scraps of copies.
    """
    # Workers serve all stages, so the tokenizer keeps fewer words, and goes when its task ends.
    return packing.packed_documents(templates.deduplicated(docs, templates.ONLY_PASSAGES), cached_words=60_000, keep=False)


STAGES = [("quality", quality_stage), ("line dedup", line_stage), ("near copies", near_copy_stage), ("packing", packing_stage)]

#: Neither the fitted classifier nor the tokenizer can be said in SQL; the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = staged(docs, f"stage-{i}")
    return docs
