"""A training corpus from ``documents``: five stages, each over all that its predecessor kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from geocensus.llm import exact_dedup, mixing, near_dup, piece_codec, toxicity
from geocensus.llm.queries import model_path, read
from geocensus.llm.shared import materialise


def reject_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity machine rejects go; it is fitted on the labelled rows of this stage's input.  Null and empty texts stay,
    and without labels of both classes every row does."""
    return toxicity.drop_toxic(docs, read(spark, sf_dir, "labels"))


def exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of equal texts stays; null counts as empty, so one of the empty texts does."""
    return exact_dedup.drop_exact_duplicates(docs)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near copies stays; texts without words are classes of their own."""
    return near_dup.drop_near_duplicates(docs)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix of sources takes them; texts without words are never taken, a null source is one of its own."""
    return mixing.mix_table(docs)


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of ids and decoded text of every document, repeats included; null counts as empty and has no ids."""
    return piece_codec.encode_digest(docs, model_path())


STAGES = [("toxicity", reject_toxic), ("exact dedup", exact_copies), ("n-gram Jaccard join", near_copies), ("mixing", mixed), ("SentencePiece", encoded)]
#: SQL cannot express the first, third and last stage.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on ``documents``; what a stage returns is written as Parquet and read again."""
    docs = read(spark, sf_dir, "documents")
    for n, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if n < len(STAGES) - 1:
            docs = materialise(docs, f"pipeline-{name.replace(' ', '-')}")
    return docs
