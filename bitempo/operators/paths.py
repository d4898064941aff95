"""Node-simple time-respecting paths between two nodes."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..lineage import cut


def _latest_departures(edges: DataFrame, dst: int, hops: int) -> list[DataFrame]:
    """For 0, 1, … hops left: (node, latest) by when the node must be reached at the latest; a necessary condition."""
    levels = []
    known = None
    for h in range(hops):
        if h == 0:
            now = edges.where(F.col("dst") == dst).groupBy("src").agg((F.max("t") - 1).alias("latest"))
        else:
            on = edges.join(known.select(F.col("node").alias("dst"), F.col("latest").alias("must")), "dst").where(F.col("t") <= F.col("must"))
            now = on.groupBy("src").agg((F.max("t") - 1).alias("latest")).unionByName(known.select(F.col("node").alias("src"), "latest")).groupBy("src").agg(F.max("latest").alias("latest"))
        known = cut(now.select(F.col("src").alias("node"), "latest"))
        levels.append(known)
    return levels


def time_respecting_paths(edges: DataFrame, src: int, dst: int, t_from: int, t_to: int, k: int = 20, max_hops: int = 4, max_wait: int | None = None) -> DataFrame:
    """(rank, nodes, eids, departs, arrives, hops): the first ``k`` <= 20 paths by arrival, hops and edge ids.

    Paths grow by a hop a round; a partial path stays only while its end can still reach the goal in the hops that are left.
    """
    if not 1 <= k <= 20:
        raise ValueError("k must be from 1 to 20")
    live = cut(edges.where((F.col("t") > t_from) & (F.col("t") <= t_to) & (F.col("src") != F.col("dst"))).select("eid", "src", "dst", "t"))
    levels = _latest_departures(live, dst, max_hops)
    paths = live.where(F.col("src") == src).select(F.array("src", "dst").alias("nodes"), F.array("eid").alias("eids"), F.col("t").alias("departs"), F.col("t").alias("arrives"), F.col("dst").alias("end"))
    found = None
    order = Window.orderBy("arrives", "hops", "eids")
    for hop in range(1, max_hops + 1):
        done = paths.where(F.col("end") == dst).withColumn("hops", F.lit(hop)).orderBy("arrives", "eids").limit(k)
        found = done if found is None else found.unionByName(done)
        if hop == max_hops:
            break
        left = levels[max_hops - hop - 1].select(F.col("node").alias("end"), "latest")
        open_paths = paths.where(F.col("end") != dst).join(left, "end").where(F.col("arrives") <= F.col("latest"))
        step = open_paths.join(live.select("eid", F.col("src").alias("end"), F.col("dst").alias("next"), "t"), "end").where((F.col("t") > F.col("arrives")) & ~F.array_contains("nodes", F.col("next")))
        if max_wait is not None:
            step = step.where(F.col("t") - F.col("arrives") <= max_wait)
        paths = cut(step.select(F.concat("nodes", F.array("next")).alias("nodes"), F.concat("eids", F.array("eid")).alias("eids"), "departs", F.col("t").alias("arrives"), F.col("next").alias("end")))
    best = found.orderBy("arrives", "hops", "eids").limit(k)
    return best.withColumn("rank", F.row_number().over(order)).select("rank", "nodes", "eids", "departs", "arrives", "hops")
