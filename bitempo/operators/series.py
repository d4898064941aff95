"""Bucketed statistics of a graph, and bursts in a series."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.canon import canon_float
from ..functions.timeaxis import floor_to


def metric_series(edges: DataFrame, t_from: int, t_to: int, width: int) -> DataFrame:
    """(bucket, nodes, edges, deg_mean, deg_max, reciprocity) of [t_from, t_to), empty buckets as zeros.

    Reciprocity is the share of distinct ordered pairs whose reverse is in the same bucket. Edges are reduced to links of a
    bucket first, map-side; links give the degrees; links, degrees and the frame of empty buckets meet in one aggregate without a join.
    """
    inside = edges.where((F.col("t") >= t_from) & (F.col("t") < t_to) & (F.col("src") != F.col("dst")))
    bucket = (F.lit(t_from) + floor_to(F.col("t") - t_from, width)).alias("bucket")
    up = F.col("src") < F.col("dst")
    links = inside.groupBy(bucket, F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).agg(F.count(F.when(up, 1)).alias("ups"), F.count(F.when(~up, 1)).alias("downs"))
    links = links.select("bucket", "a", "b", (F.col("ups") + F.col("downs")).alias("n"), ((F.col("ups") > 0).cast("long") + (F.col("downs") > 0).cast("long")).alias("ways"))
    # one row for each end of a link; the link's own figures go with its first end
    first = F.col("i") == 0
    ends = links.select("bucket", "n", "ways", F.posexplode(F.array("a", "b")).alias("i", "node"))
    degrees = ends.groupBy("bucket", "node").agg(F.sum("n").alias("degree"), F.sum(F.when(first, F.col("n"))).alias("edges"), F.sum(F.when(first, F.col("ways"))).alias("pairs"), F.sum(F.when(first & (F.col("ways") == 2), 2)).alias("mutual"))
    none = [F.lit(None).cast("long").alias(c) for c in ("degree", "edges", "pairs", "mutual")]
    frame = edges.sparkSession.range(0, -(-(t_to - t_from) // width)).select((F.lit(t_from) + F.col("id") * width).alias("bucket"), *none)
    stats = degrees.drop("node").unionByName(frame).groupBy("bucket").agg(
        F.count("degree").alias("nodes"), F.sum("degree").alias("ends"), F.max("degree").alias("deg_max"), F.sum("edges").alias("edges"), F.sum("pairs").alias("pairs"), F.sum("mutual").alias("mutual")
    )
    zero = lambda c: F.coalesce(F.col(c), F.lit(0)).cast("long").alias(c)
    return stats.select(
        "bucket", zero("nodes"), zero("edges"), F.when(F.col("nodes") > 0, canon_float(F.col("ends") / F.col("nodes"))).otherwise(0.0).alias("deg_mean"), zero("deg_max"),
        F.when(F.col("pairs") > 0, canon_float(F.coalesce("mutual", F.lit(0)) / F.col("pairs"))).otherwise(0.0).alias("reciprocity"),
    )


def event_counts(edges: DataFrame, t_from: int, t_to: int, width: int) -> DataFrame:
    """(bucket, value): edge events of each bucket, zeros included."""
    inside = edges.where((F.col("t") >= t_from) & (F.col("t") < t_to))
    counted = inside.groupBy((F.lit(t_from) + floor_to(F.col("t") - t_from, width)).alias("bucket")).agg(F.count(F.lit(1)).alias("n"))
    frame = edges.sparkSession.range(0, -(-(t_to - t_from) // width)).select((F.lit(t_from) + F.col("id") * width).alias("bucket"))
    return frame.join(counted, "bucket", "left").select("bucket", F.coalesce("n", F.lit(0)).cast("double").alias("value"))


def detect_bursts(series: DataFrame, rule: str, lookback: int, threshold: float, least: float = 1.0, by: list[str] | None = None) -> DataFrame:
    """(…by, bucket, value, baseline, score, is_burst) of ``series(…by, bucket, value)``.

    ``zscore``: distance from the mean of the ``lookback`` buckets before, in their standard deviations. ``median``: value over their median; a
    zero median makes a burst of any value of at least ``least``. Scores are canonical before they meet the threshold.
    """
    before = Window.partitionBy(*(by or [])).orderBy("bucket").rowsBetween(-lookback, -1)
    enough = F.count("value").over(before) == lookback
    if rule == "zscore":
        mean, spread = F.avg("value").over(before), F.stddev_pop("value").over(before)
        s = series.withColumn("baseline", F.when(enough, canon_float(mean))).withColumn("_sd", F.when(enough, canon_float(spread)))
        s = s.withColumn("score", F.when(F.col("_sd") > 0, canon_float((F.col("value") - F.col("baseline")) / F.col("_sd"))))
        burst = F.coalesce(F.col("score") >= threshold, F.lit(False))
    elif rule == "median":
        s = series.withColumn("baseline", F.when(enough, canon_float(F.percentile("value", F.lit(0.5)).over(before))))
        s = s.withColumn("score", F.when(F.col("baseline") > 0, canon_float(F.col("value") / F.col("baseline"))))
        burst = F.coalesce(F.when(F.col("baseline") == 0, F.col("value") >= least).otherwise(F.col("score") >= threshold), F.lit(False))
    else:
        raise ValueError("rule must be zscore or median")
    return s.withColumn("is_burst", burst).select(*(by or []), "bucket", "value", "baseline", "score", "is_burst")
