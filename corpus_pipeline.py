"""The corpus pipeline: language ID, toxicity, near-duplicates, mixing to target weights, packing.

Each stage takes the documents that its predecessor kept and returns them with the columns of ``documents``; the last
returns packed pieces. Null texts: language ID rejects them, as all texts without a letter. Empty tables stay empty.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bitempo.llm import language, mixing, packing, simhash, toxicity
from bitempo.llm.common import fold_of, stash, table


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language can be told go on; texts without a letter do not."""
    profiles = language.train(docs.where(fold_of("doc_id", 4) != 2))
    if not profiles:
        return docs.where(F.lit(False))
    return docs.where(language.predicted(F.col("text"), profiles)["lang_pred"] != language.UNKNOWN)


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score under the threshold go on."""
    labels = table(spark, sf_dir, "labels", "doc_id", "toxic").where(fold_of("doc_id", 3) != 1)
    model = toxicity.train(docs, labels)
    return docs.where(toxicity.tagged(F.col("text"), model)["score"] < toxicity.THRESHOLD)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class goes on."""
    return simhash.one_of_each_class(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents go on as often as the mix takes them."""
    return mixing.mixed_documents(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sequences of the documents' tokens."""
    return packing.packed(docs)


STAGES = [
    ("language", identify_language),
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("mixing", mix_sources),
    ("packing", pack),
]

#: Several stages are models or searches that SQL cannot express; tests compare them with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = stash(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
