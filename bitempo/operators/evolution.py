"""How a node's neighbourhood changes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.timeaxis import floor_to


def _neighbours(edges: DataFrame, node: int) -> DataFrame:
    mine = edges.where((F.col("src") == node) | (F.col("dst") == node)).where("src != dst")
    return mine.select(F.when(F.col("src") == node, F.col("dst")).otherwise(F.col("src")).alias("neighbour"), "t")


def neighbour_changes(edges: DataFrame, node: int, w1: tuple[int, int], w2: tuple[int, int]) -> DataFrame:
    """(neighbour, change) with change gained, lost or kept from window ``w1`` to ``w2``; one scan, one aggregate."""
    inside = lambda w: (F.col("t") >= w[0]) & (F.col("t") < w[1])
    seen = _neighbours(edges, node).where(inside(w1) | inside(w2)).groupBy("neighbour").agg(F.bool_or(inside(w1)).alias("was"), F.bool_or(inside(w2)).alias("now"))
    return seen.select("neighbour", F.when(~F.col("was"), "gained").when(~F.col("now"), "lost").otherwise("kept").alias("change"))


def degree_series(edges: DataFrame, node: int, t_from: int, t_to: int, width: int) -> DataFrame:
    """(bucket, degree, neighbours) of one node, zeros included."""
    inside = _neighbours(edges, node).where((F.col("t") >= t_from) & (F.col("t") < t_to))
    per = inside.groupBy((F.lit(t_from) + floor_to(F.col("t") - t_from, width)).alias("bucket")).agg(F.count(F.lit(1)).alias("degree"), F.countDistinct("neighbour").alias("neighbours"))
    frame = edges.sparkSession.range(0, -(-(t_to - t_from) // width)).select((F.lit(t_from) + F.col("id") * width).alias("bucket"))
    zero = lambda c: F.coalesce(F.col(c), F.lit(0)).cast("long").alias(c)
    return frame.join(per, "bucket", "left").select("bucket", zero("degree"), zero("neighbours"))
