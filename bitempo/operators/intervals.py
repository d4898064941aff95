"""Interval pairs of two selections by Allen's relations."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.timeaxis import ALLEN, HOUR
from .bandjoin import interval_join, relation_totals


def interval_pairs(a: DataFrame, b: DataFrame, relations: tuple[str, ...] = ALLEN, keys: tuple[str, ...] = (), width: int = HOUR) -> DataFrame:
    """(a_id, b_id, relation) of ``a`` and ``b`` (id, i_s, i_e, keys); instants are widened to a microsecond."""
    unknown = set(relations) - set(ALLEN)
    if unknown:
        raise ValueError(f"no such relation: {sorted(unknown)}")
    side = lambda df, n: df.select(*keys, F.col("id").alias(f"{n}_id"), F.col("i_s").alias(f"{n}_s"), F.greatest(F.col("i_e"), F.col("i_s") + 1).alias(f"{n}_e"))
    return interval_join(side(a, "a"), side(b, "b"), list(keys), relations, width).select("a_id", "b_id", "relation")


def relation_counts(a: DataFrame, b: DataFrame, keys: tuple[str, ...], width: int = HOUR) -> DataFrame:
    """(relation, pairs) for all thirteen; far pairs are counted from ranks and never made."""
    side = lambda df, n: df.select(*keys, F.col("id").alias(f"{n}_id"), F.col("i_s").alias(f"{n}_s"), F.greatest(F.col("i_e"), F.col("i_s") + 1).alias(f"{n}_e"))
    left, right = side(a, "a"), side(b, "b")
    near = interval_join(left, right, list(keys), tuple(r for r in ALLEN if r not in ("before", "after")), width).groupBy("relation").agg(F.count(F.lit(1)).alias("pairs"))
    far = relation_totals(left, right, list(keys)).agg(F.sum("before").alias("before"), F.sum("after").alias("after"))
    far = far.select(F.explode(F.array(*[F.struct(F.lit(r).alias("relation"), F.coalesce(F.col(r), F.lit(0)).cast("long").alias("pairs")) for r in ("before", "after")])).alias("x")).select("x.*")
    return near.unionByName(far.where("pairs > 0"))
