"""Five stages from raw documents to token digests: each takes what the one before kept, as written and read again."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from multiway.llm.bpe import encoded
from multiway.llm.common import stored, table
from multiway.llm.decontaminate import without_contaminated
from multiway.llm.neardup import keep_one
from multiway.llm.quality import fit_quality, of_quality
from multiway.llm.substring import without_repeats
from multiway.session import ship


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier holds for good (score of 0.5 or more)."""
    ship(spark)
    return of_quality(docs, fit_quality(docs, table(spark, sf_dir, "labels")))


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near copies, one with the smallest id."""
    ship(spark)
    return keep_one(docs)


def substring_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the words of passages that a document with a smaller id has; a document left without a word goes.

    A text that loses nothing stays as it is; one that does has its words joined by blanks.
    """
    ship(spark)
    return without_repeats(docs)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a window of the benchmark."""
    ship(spark)
    return without_contaminated(docs, table(spark, sf_dir, "benchmark"))


def tokens_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Number of tokens and digests of ids and of the decoded bytes."""
    ship(spark)
    return encoded(docs, ["doc_id"])


STAGES = [("quality classifier", quality_stage), ("n-gram Jaccard join", near_duplicate_stage), ("substring dedup", substring_stage), ("benchmark decontamination", decontamination_stage), ("byte-level BPE", tokens_stage)]

#: The trained classifier and the forest can't be written in SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents."""
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = stored(docs)
    return docs
