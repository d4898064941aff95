"""Earliest arrival over time-respecting paths, exact with and without wait limits.

A path leaves a node after it arrived there (``strict``) and within the wait limits; the departure from a source is free of them
unless ``source_waits``. Three ways to the same result:

- without a limit one label a node suffices: rounds relax the frontier's edges and keep improvements;
- with a limit a later arrival can be the one that connects, so all labels (node, arrival) are searched, each live edge once;
- the sweep goes through slices of time; within one, an edge is live if the latest live arrival before it is near enough, which is
  one window over arrivals and departures; a node's state between slices is two numbers, whatever its number of labels.
"""

from __future__ import annotations

from itertools import count

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..lineage import cut


def _departs(t: Column, arrival: Column, at_source: Column, max_wait: int | None, min_wait: int, strict: bool) -> Column:
    ok = (t > arrival) if strict else (t >= arrival)
    waits = F.lit(True)
    if min_wait:
        waits = waits & (t - arrival >= min_wait)
    if max_wait is not None:
        waits = waits & (t - arrival <= max_wait)
    return ok & (at_source | waits)


def _window_edges(edges: DataFrame, t_from: int, t_to: int) -> DataFrame:
    return edges.where((F.col("t") >= t_from) & (F.col("t") <= t_to) & (F.col("src") != F.col("dst"))).select("eid", "src", "dst", "t")


def reach_unlimited(edges: DataFrame, sources: DataFrame, t_from: int, t_to: int, strict: bool = True) -> DataFrame:
    """(source, node, arrival) without wait limits, in as many rounds as the longest chain of improvements has edges.

    Each round writes its improvements alone; they are put together with what was known every eighth round.
    """
    live = cut(_window_edges(edges, t_from, t_to).select("src", "dst", "t"))
    best = cut(sources.select(F.col("node").alias("source"), "node").distinct().withColumn("arrival", F.lit(t_from).cast("long")))
    frontier, least = best, F.min("arrival").alias("arrival")
    for n in count(1):
        t = F.col("t")
        step = frontier.join(live, frontier["node"] == live["src"]).where(t > F.col("arrival") if strict else t >= F.col("arrival"))
        found = step.groupBy("source", F.col("dst").alias("node")).agg(F.min("t").alias("arrival"))
        known = best.groupBy("source", "node").agg(F.min("arrival").alias("known"))
        frontier = cut(found.join(known, ["source", "node"], "left").where("known is null or arrival < known").select("source", "node", "arrival"))
        if frontier.isEmpty():
            return best.groupBy("source", "node").agg(least)
        best = best.unionByName(frontier)
        best = cut(best.groupBy("source", "node").agg(least)) if n % 8 == 0 else best


def live_labels(edges: DataFrame, sources: DataFrame, t_from: int, t_to: int, max_wait: int | None, min_wait: int = 0, strict: bool = True, source_waits: bool = False, max_hops: int | None = None) -> DataFrame:
    """(source, node, arrival, hops): every reachable label at its least number of hops."""
    live = cut(_window_edges(edges, t_from, t_to).select("src", "dst", "t").distinct())
    start = sources.select(F.col("node").alias("source"), "node").distinct().withColumns({"arrival": F.lit(t_from).cast("long"), "hops": F.lit(0)})
    seen = frontier = cut(start)
    for hop in count(1):
        if max_hops is not None and hop > max_hops:
            return seen
        at_source = (F.col("hops") == 0) & F.lit(not source_waits)
        step = frontier.join(live, frontier["node"] == live["src"]).where(_departs(F.col("t"), F.col("arrival"), at_source, max_wait, min_wait, strict))
        found = step.select("source", F.col("dst").alias("node"), F.col("t").alias("arrival")).distinct()
        frontier = cut(found.join(seen, ["source", "node", "arrival"], "left_anti").withColumn("hops", F.lit(hop)))
        if frontier.isEmpty():
            return seen
        seen = seen.unionByName(frontier)
        seen = cut(seen) if hop % 8 == 0 else seen


def sweep_arrivals(edges: DataFrame, source: int, t_from: int, t_to: int, max_wait: int | None, slice_us: int, strict: bool = True) -> DataFrame:
    """(node, arrival) by slices of time, for one source without least wait; a node's state is its first and latest arrival."""
    if not strict:
        raise ValueError("the sweep is for strict steps")
    spark = edges.sparkSession
    window_edges = cut(_window_edges(edges, t_from, t_to).select("src", "dst", "t").withColumn("slice", F.floor((F.col("t") - t_from) / F.lit(slice_us)).cast("int")))
    state = spark.createDataFrame([(source, t_from, t_from)], "node long, first long, latest long")
    for n in [r[0] for r in window_edges.select("slice").distinct().orderBy("slice").collect()]:
        part = window_edges.where(F.col("slice") == n)
        arrivals = state.select("node", F.col("latest").alias("at"))
        while True:
            # departures of every node among its arrivals: the last arrival before each decides
            both = part.select(F.col("src").alias("node"), F.col("t").alias("at"), "dst").withColumn("arr", F.lit(None).cast("long")).unionByName(
                arrivals.select("node", "at", F.lit(None).cast("long").alias("dst"), F.col("at").alias("arr"))
            )
            last = F.last("arr", ignorenulls=True).over(Window.partitionBy("node").orderBy("at").rangeBetween(Window.unboundedPreceding, -1))
            timely = F.lit(True) if max_wait is None else ((F.col("at") - F.col("last") <= max_wait) | ((F.col("node") == source) & (F.col("last") == t_from)))
            # leaving the source is free of the limit whenever it is seen from its start
            free = F.lit(False) if max_wait is None else (F.col("node") == source)
            live = both.withColumn("last", last).where(F.col("dst").isNotNull() & F.col("last").isNotNull() & (timely | free)).select(F.col("dst").alias("node"), "at").distinct()
            new = cut(live.join(arrivals, ["node", "at"], "left_anti"))
            if new.isEmpty():
                break
            arrivals = cut(arrivals.unionByName(new))
        merged = arrivals.groupBy("node").agg(F.min("at").alias("first2"), F.max("at").alias("latest2"))
        state = cut(merged.join(state, "node", "left").select("node", F.least("first", "first2").alias("first"), F.greatest("latest", "latest2").alias("latest")))
    return state.select("node", F.col("first").alias("arrival"))


def earliest_arrival(
    edges: DataFrame, sources: DataFrame, t_from: int, t_to: int, max_wait: int | None = None, min_wait: int = 0, strict: bool = True,
    max_hops: int | None = None, targets: list[int] | None = None, source_waits: bool = False,
) -> DataFrame:
    """(source, node, arrival) of every reachable node, sources at ``t_from``; with ``max_hops`` or limits also exact."""
    if max_wait is None and not min_wait and max_hops is None:
        best = reach_unlimited(edges, sources, t_from, t_to, strict)
    else:
        labels = live_labels(edges, sources, t_from, t_to, max_wait, min_wait, strict, source_waits, max_hops)
        best = labels.groupBy("source", "node").agg(F.min("arrival").alias("arrival"))
    return best if targets is None else best.where(F.col("node").isin(*targets))


def arrival_hops(edges: DataFrame, sources: DataFrame, t_from: int, t_to: int, max_wait: int | None = None, strict: bool = True) -> DataFrame:
    """(source, node, arrival, hops) with the fewest hops among paths that attain the earliest arrival."""
    labels = live_labels(edges, sources, t_from, t_to, max_wait, strict=strict)
    return labels.groupBy("source", "node").agg(F.min(F.struct("arrival", "hops")).alias("b")).select("source", "node", "b.arrival", "b.hops")


def earliest_arrival_greedy(edges: DataFrame, sources: DataFrame, t_from: int, t_to: int, max_wait: int, rounds: int = 200) -> DataFrame:
    """The wrong rule, kept as a control: under a wait limit, too, a node departs from its earliest arrival alone."""
    live = cut(_window_edges(edges, t_from, t_to).select("src", "dst", "t"))
    start = cut(sources.select(F.col("node").alias("source"), "node").distinct().withColumn("arrival", F.lit(t_from).cast("long")))
    best, known = start, None
    for _ in range(rounds):
        step = best.join(live, best["node"] == live["src"]).where(_departs(F.col("t"), F.col("arrival"), F.col("node") == F.col("source"), max_wait, 0, True))
        found = step.select("source", F.col("dst").alias("node"), F.col("t").alias("arrival")).unionByName(start)
        best = cut(found.groupBy("source", "node").agg(F.min("arrival").alias("arrival")))
        state = tuple(best.agg(F.count(F.lit(1)), F.sum(F.col("arrival").cast("decimal(38,0)"))).first())
        if state == known:
            return best
        known = state
    raise RuntimeError(f"the greedy rule did not settle in {rounds} rounds")
