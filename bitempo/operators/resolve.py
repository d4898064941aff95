"""From names to identifiers: the only way in for an identifier that the task does not state."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import fold_name
from ..sources.tables import load_table

MODES = ("id", "exact", "folded", "prefix", "fuzzy")


def names_table(spark: SparkSession, sf_dir: str, types: tuple[str, ...] = ("customer", "supplier", "nation", "region", "part")) -> DataFrame:
    """(type, ident, name) of everything that has a name."""
    out = None
    for kind in types:
        p = {"customer": "c", "supplier": "s", "nation": "n", "region": "r", "part": "p"}[kind]
        key = {"customer": "c_custkey", "supplier": "s_suppkey", "nation": "n_nationkey", "region": "r_regionkey", "part": "p_partkey"}[kind]
        rows = load_table(spark, sf_dir, kind, key, f"{p}_name").select(F.lit(kind).alias("type"), F.col(key).cast("long").alias("ident"), F.col(f"{p}_name").alias("name"))
        out = rows if out is None else out.unionByName(rows)
    return out


def resolve_names(names: DataFrame, text: str, mode: str = "folded", types: list[str] | None = None, most_edits: int = 2) -> DataFrame:
    """(ident, type, name, score, ambiguous): matches of ``text``; ambiguous if its best score belongs to several."""
    if mode not in MODES:
        raise ValueError(f"mode must be one of {MODES}")
    names = names if types is None else names.where(F.col("type").isin(*types))
    wanted = F.lit(text)
    folded = fold_name(wanted)
    if mode == "id":
        hits = names.where(F.col("ident").cast("string") == wanted).withColumn("score", F.lit(1.0))
    elif mode == "exact":
        hits = names.where(F.col("name") == wanted).withColumn("score", F.lit(1.0))
    elif mode == "folded":
        hits = names.where(fold_name("name") == folded).withColumn("score", F.lit(1.0))
    elif mode == "prefix":
        hits = names.where(F.startswith(fold_name("name"), folded)).withColumn("score", F.round(F.char_length(folded) / F.char_length(fold_name("name")), 6))
    else:
        near = F.levenshtein(fold_name("name"), folded, most_edits)
        hits = names.withColumn("_d", near).where("_d >= 0").withColumn("score", F.round(1 - F.col("_d") / F.greatest(F.char_length(folded), F.char_length(fold_name("name"))), 6))
    # what ties with the best score is ambiguous; hits of one text are few against the names
    best = hits.agg(F.max("score").alias("top"))
    tied = hits.groupBy("score").agg(F.count(F.lit(1)).alias("n"))
    counted = hits.join(tied, "score").join(F.broadcast(best), F.lit(True))
    return counted.select("ident", "type", "name", "score", ((F.col("score") == F.col("top")) & (F.col("n") > 1)).alias("ambiguous"))


def user_ids(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias("ident")).distinct().select(F.lit("user").alias("type"), "ident", F.col("ident").cast("string").alias("name"))


__all__ = ["MODES", "names_table", "resolve_names", "user_ids"]
