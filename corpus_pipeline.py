"""A training corpus in five stages, each on all that the one before it kept.

Quality, one document of each near-duplicate group, benchmark decontamination, mixing to target
weights, packed token ids. Every stage's result is written as Parquet and read again for the next.

Null and empty texts, null ids, repeated rows and further columns go through each stage as its operator's
docstring says; empty tables give empty results; a stage that filters keeps all columns.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tilesieve.llm import curriculum, decontam, jaccard, quality
from tilesieve.llm.bitpack import packed_documents, stored_order
from tilesieve.llm.common import stored
from tilesieve.llm.registry import table, word_tokenizer

#: Near duplicates of the corpus share 0.8 of their five-word shingles; four words and 0.85 are the query's alone.
NEAR_WORDS = 5
NEAR_PERCENT = 80


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality model accepts; it learns from those labelled outside the held-out fold."""
    return quality.keep_good(docs, quality.train(docs, table(spark, sf_dir, "labels")))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of the Jaccard join, at this stage's own width and similarity."""
    return jaccard.keep_one(docs, n=NEAR_WORDS, percent=NEAR_PERCENT)


def drop_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no region of a benchmark item."""
    return decontam.drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row for each copy that the mix takes, in training order: that of the files and of the rows in them."""
    return curriculum.mixed_documents(docs, position=None)


def pack_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Where each copy's ids stand in the packed files, which keep the training order of the stage before.

    Rows that come from no file have no such order and are packed by id.
    """
    return packed_documents(docs, word_tokenizer(), order=stored_order(docs))


STAGES = [
    ("quality", keep_quality),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_benchmark),
    ("mixing", mix_sources),
    ("token_ids", pack_tokens),
]

#: Models, components and a tokenizer are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = stored(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs
