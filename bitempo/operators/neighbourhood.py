"""k-hop neighbourhoods of a snapshot."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


#: A frontier of at most so many nodes is read to the driver and sent with the scan; a larger one stays distributed.
SMALL_FRONTIER, LITERALS = 10_000, 200


def both_ways(edges: DataFrame, direction: str) -> DataFrame:
    out = edges.select(F.col("src").alias("node"), F.col("dst").alias("next"))
    back = edges.select(F.col("dst").alias("node"), F.col("src").alias("next"))
    return {"out": out, "in": back, "both": out.unionByName(back)}[direction]


def _bounded(nodes: DataFrame) -> list[int] | None:
    """The nodes, or None if there are more than a small frontier has."""
    rows = [r[0] for r in nodes.select("node").distinct().limit(SMALL_FRONTIER + 1).collect()]
    return rows if len(rows) <= SMALL_FRONTIER else None


def _literal(edges: DataFrame, nodes: list[int], hop: int) -> DataFrame:
    """(node, hop) of a small frontier as a literal, without a job or a Python worker."""
    one = edges.sparkSession.range(1)
    rows = one.select(F.explode(F.array(*[F.lit(n).cast("long") for n in nodes])).alias("node")) if nodes else one.select(F.col("id").alias("node")).limit(0)
    return rows.withColumn("hop", F.lit(hop))


def _next_of(links: DataFrame, frontier: DataFrame, known: list[int] | None) -> DataFrame:
    if known is not None and len(known) <= LITERALS:
        return links.where(F.col("node").isin(known)).select(F.col("next").alias("node")).distinct()
    side = frontier.select("node") if known is None else F.broadcast(_literal(links, known, 0).select("node"))
    return links.join(side, "node").select(F.col("next").alias("node")).distinct()


def khop_neighbourhood(edges: DataFrame, seeds: DataFrame, k: int, direction: str = "out") -> DataFrame:
    """(node, hop) within ``k`` <= 3 hops of ``seeds(node)``, each at its least hop.

    Each hop is one scan of the edges. While the frontier is small, which is checked, the scan filters by it and no edge is shuffled;
    a large frontier is joined and what was visited is taken off by an anti join.
    """
    if not 1 <= k <= 3:
        raise ValueError("k must be 1, 2 or 3")
    links = both_ways(edges, direction)
    frontier = seeds.select("node").distinct()
    known = _bounded(frontier)
    seen: list[int] | None = known
    visited = frontier.withColumn("hop", F.lit(0)) if known is None else _literal(edges, known, 0)
    for hop in range(1, k + 1):
        reached = _next_of(links, frontier, known)
        if seen is not None and len(seen) <= LITERALS:
            frontier = reached.where(~F.col("node").isin(seen)) if seen else reached
        else:
            frontier = reached.join(visited.select("node"), "node", "left_anti")
        if hop < k:
            known = _bounded(frontier)
            if known is not None:
                frontier = _literal(edges, known, hop).select("node")
                seen = seen + known if seen is not None else None
            else:
                seen = None
        visited = visited.unionByName(frontier.withColumn("hop", F.lit(hop)))
    return visited


def induced_edges(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    from .selection import restrict_nodes

    return restrict_nodes(edges, nodes)


def snapshot_edges(edges: DataFrame, t: int, ttl: int) -> DataFrame:
    """Edge events as versions that hold for ``ttl`` from their instant: those that cover ``t``. One range on t, pushed to the scan."""
    return edges.where((F.col("t") <= t) & (F.col("t") > t - ttl))
