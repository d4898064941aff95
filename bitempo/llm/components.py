"""Connected components of a link table, by alternating large-star and small-star steps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stash


def _toward_least(sides: DataFrame, keep, also_self: bool) -> DataFrame:
    """Link the neighbours of each node that ``keep`` admits to the least node of its neighbourhood.

    The least node is a partial aggregate that joins back, so a node with very many links is dealt over tasks by the skew join.
    """
    least = sides.groupBy("u").agg(F.min("v").alias("w")).select("u", F.least("u", "w").alias("w"))
    moved = sides.where(keep).join(least, "u").select(F.col("v").alias("u"), F.col("w").alias("v"))
    if also_self:
        moved = moved.unionByName(least.select("u", F.col("w").alias("v")))
    return moved.where("u != v").distinct()


def components(links: DataFrame, rounds: int = 60) -> DataFrame:
    """(node, root) for every node of ``links(u, v)``; the root is the least node that can be reached.

    Self links and repeated links do no harm; an empty table gives an empty table. Every round's links are written
    to the shared folder. The number of rounds grows with the logarithm of the longest chain.
    """
    links = stash(links.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u != v").distinct(), "links")
    state = None
    for _ in range(rounds):
        both = links.unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = stash(_toward_least(both, F.col("v") > F.col("u"), also_self=False), "links")
        small = large.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
        links = stash(_toward_least(small, F.lit(True), also_self=True), "links")
        seen = links.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if tuple(seen) == state:
            roots = links.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
            return links.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(roots)
        state = tuple(seen)
    raise RuntimeError(f"components did not settle in {rounds} rounds")
