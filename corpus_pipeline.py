"""From raw documents to packed training sequences: five stages, each a table that the next one reads."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fpfilter.llm import exact_dedup, mixing, near_dedup, packing, toxicity
from fpfilter.llm.scratch import fresh, written


def clean(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity machine, fitted on the labels of these documents, does not reject (score below 0.5).

    Null and empty texts have the score of no terms; repeated rows stay or go together; without labels all texts get one
    score, and stay. Extra columns of any name stay as they are. An empty table gives no rows.
    """
    machine = toxicity.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    (score,) = fresh(docs, "score")
    return toxicity.scored(docs, machine, to=score).where(F.col(score) < 0.5).drop(score)


def unique(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts, whatever their length, the document with the largest id; null text equals empty text.

    Null ids are the smallest; of rows that tie one stays. Extra columns stay. An empty table gives no rows.
    """
    return exact_dedup.survivors(docs)


def distinct(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate component, that of the smallest id: five-word shingles, similarity of 0.8.

    Whole texts count; documents without words, and null ones, are components of their own; rows with that id and text
    stay together. Extra columns stay. An empty table gives no rows.
    """
    return near_dedup.survivors(docs)


def balanced(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix of sources takes them, in the order of its schedule.

    Documents without words, and null ones, are left out; null sources are one source; repeated rows come as often
    each. Extra columns stay. An empty table gives no rows.
    """
    return mixing.repeated(docs)


def sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of documents in training sequences; see :func:`fpfilter.llm.packing.packed` for awkward rows."""
    return packing.packed(docs)


STAGES = [("toxicity", clean), ("exact_dedup", unique), ("near_dedup", distinct), ("mixing", balanced), ("packing", sequences)]

#: The first and third stages are beyond SQL; tests hold every stage against a plain computation.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on ``documents`` of ``sf_dir``, each written and read again; an empty table ends in no pieces."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs
