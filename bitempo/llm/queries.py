"""Queries of the training-data operators: each applies one operator to its whole table with production parameters."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from pyspark.sql import functions as F

from .common import fold_of, table
from .mixing import ORACLE as ORACLE_MIXING
from .topk import ORACLE as ORACLE_TOPK


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .toxicity import THRESHOLD, tagged, train

    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    labels = table(spark, sf_dir, "labels", "doc_id", "toxic")
    model = train(docs, labels.where(fold_of("doc_id", 3) != 1))
    found = docs.select("doc_id", (fold_of("doc_id", 3) == 1).alias("held_out"), tagged(F.col("text"), model).alias("t"))
    return found.select("doc_id", "held_out", "t.score", (F.col("t.score") >= THRESHOLD).cast("int").alias("predicted"), F.col("t.spans").alias("spans"))


def op2_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .packing import packed

    return packed(table(spark, sf_dir, "documents", "doc_id", "text"))


def op3_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .language import predicted, train

    docs = table(spark, sf_dir, "documents", "doc_id", "text", "lang")
    profiles = train(docs.where(fold_of("doc_id", 4) != 2))
    found = docs.select("doc_id", (fold_of("doc_id", 4) == 2).alias("held_out"), predicted(F.col("text"), profiles).alias("p"))
    return found.select("doc_id", "held_out", "p.lang_pred", "p.score")


def op4_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .html_text import extracted

    return extracted(table(spark, sf_dir, "pages", "page_id", "url", "html"))


def op5_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .topk import top_k

    vectors = table(spark, sf_dir, "embeddings", "vec_id", "embedding")
    return top_k(vectors, vectors.where(F.col("vec_id") % 50 == 0))


def op6_matroska(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .matroska import audio, read_back

    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    stored = docs.select("doc_id", F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes"), audio(F.col("text")).alias("media"))
    return stored.select("doc_id", "n_bytes", read_back(F.col("media")).alias("d")).select("doc_id", "n_bytes", "d.*")


def op7_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .mixing import mixed

    return mixed(table(spark, sf_dir, "documents", "doc_id", "text", "source")).drop("copies")


def op8_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .token_files import token_index

    return token_index(table(spark, sf_dir, "documents")).select("doc_id", "start", "n_tokens", "ids_crc32")


def op9_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .lm_score import scored, train

    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    good = table(spark, sf_dir, "labels", "doc_id", "quality").where((F.col("quality") == 1) & (fold_of("doc_id", 3) != 1))
    found = scored(docs, train(docs, good))
    return found.withColumn("held_out", fold_of("doc_id", 3) == 1)


def op10_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .simhash import hex_digits, near_duplicate_classes

    found = near_duplicate_classes(table(spark, sf_dir, "documents", "doc_id", "text"))
    return found.select("doc_id", hex_digits(F.col("fp")).alias("fingerprint"), "component_id")


QUERIES = {
    "op1_toxicity": op1_toxicity,
    "op2_packing": op2_packing,
    "op3_language": op3_language,
    "op4_html_text": op4_html_text,
    "op5_topk": op5_topk,
    "op6_matroska": op6_matroska,
    "op7_mixing": op7_mixing,
    "op8_token_files": op8_token_files,
    "op9_lm_score": op9_lm_score,
    "op10_simhash": op10_simhash,
}

ORACLES: dict[str, str] = {"op5_topk": ORACLE_TOPK, "op7_mixing": ORACLE_MIXING}
