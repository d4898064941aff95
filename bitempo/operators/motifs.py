"""Exact temporal motifs: patterns of edges in order of (t, eid), the last within ``delta`` of the first."""

from __future__ import annotations

from itertools import product

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .bandjoin import slice_of
from .cycles import count_cycles

Pattern = tuple[tuple[int, int], ...]

#: Named patterns: each edge as (from, to) by the order in which nodes appear.
NAMED: dict[str, Pattern] = {
    "repeat": ((0, 1), (0, 1)), "ping_pong": ((0, 1), (1, 0)), "convey": ((0, 1), (1, 2)), "out_burst": ((0, 1), (0, 2)), "in_burst": ((0, 1), (2, 1)),
    "cyclic": ((0, 1), (1, 2), (2, 0)), "feed_forward": ((0, 1), (1, 2), (0, 2)), "out_star": ((0, 1), (0, 2), (0, 3)), "in_star": ((0, 1), (2, 1), (3, 1)),
    "path": ((0, 1), (1, 2), (2, 3)), "return": ((0, 1), (1, 0), (0, 1)),
}


def three_edge_patterns() -> dict[str, Pattern]:
    """The 36 sequences of three edges on at most three nodes, numbered by first appearance: first edge (0, 1)."""
    out = {}
    ends = [(a, b) for a, b in product(range(3), repeat=2) if a != b]
    for second, third in product(ends, repeat=2):
        out[f"m{second[0]}{second[1]}_{third[0]}{third[1]}"] = ((0, 1), second, third)
    return out


def canonical(pattern: Pattern) -> Pattern:
    """Node numbers by first appearance."""
    names: dict[int, int] = {}
    return tuple((names.setdefault(a, len(names)), names.setdefault(b, len(names))) for a, b in pattern)


def motif_rows(edges: DataFrame, pattern: Pattern, delta: int) -> DataFrame:
    """(nodes, eids, t_first, t_last) of every instance.

    A chain of joins: each next edge shares at least one node with what was matched and lies in the slice of the first edge or the one after;
    where it shares two nodes both are keys. Patterns must be connected in the order given.
    """
    pattern = canonical(pattern)
    width = max(1, delta)
    base = edges.where("src != dst").select("eid", "src", "dst", "t")
    nodes = 1 + max(max(e) for e in pattern)
    a, b = pattern[0]
    first = base.select(
        F.col("eid").alias("e0"), F.col("t").alias("t0"), F.col("t").alias("t_last"), F.col("eid").alias("e_last"), F.col("src").alias(f"n{a}"), F.col("dst").alias(f"n{b}"),
        F.explode(F.array(slice_of("t", width), slice_of("t", width) + 1)).alias("slice"),
    )
    later = base.select(F.col("eid").alias("e"), F.col("src").alias("s"), F.col("dst").alias("d"), "t", slice_of("t", width).alias("at_slice"))
    known, match = {a, b}, first
    for i, (x, y) in enumerate(pattern[1:], 1):
        if x not in known and y not in known:
            raise ValueError("each edge must share a node with the edges before it")
        on = F.col("slice") == F.col("at_slice")
        if x in known:
            on = on & (F.col(f"n{x}") == F.col("s"))
        if y in known:
            on = on & (F.col(f"n{y}") == F.col("d"))
        step = match.join(later, on)
        after = (F.col("t") > F.col("t_last")) | ((F.col("t") == F.col("t_last")) & (F.col("e") > F.col("e_last")))
        step = step.where(after & (F.col("t") - F.col("t0") <= delta))
        for new, c in ((x, "s"), (y, "d")):
            if new not in known:
                for other in sorted(known):
                    step = step.where(F.col(c) != F.col(f"n{other}"))
                step = step.withColumn(f"n{new}", F.col(c))
                known.add(new)
        # the slice column holds both slices of the first edge; the pair that met stays in one of them, so open it again
        keep = [f"n{j}" for j in sorted(known)] + ["t0"] + [f"e{j}" for j in range(i)]
        match = step.select(*keep, F.col("e").alias(f"e{i}"), F.col("t").alias("t_last"), F.col("e").alias("e_last"))
        if i + 1 < len(pattern):
            match = match.withColumn("slice", F.explode(F.array(slice_of("t0", width), slice_of("t0", width) + 1)))
    return match.select(F.array(*[f"n{j}" for j in range(nodes)]).alias("nodes"), F.array(*[f"e{j}" for j in range(len(pattern))]).alias("eids"), F.col("t0").alias("t_first"), "t_last")


def count_pairs_by_window(edges: DataFrame, delta: int, pattern: Pattern) -> DataFrame:
    """Counts of two-edge patterns on one pair of nodes (repeat, ping-pong) by a running count, without making rows."""
    pattern = canonical(pattern)
    if pattern not in (NAMED["repeat"], NAMED["ping_pong"]):
        raise ValueError("a pattern of two edges between the same two nodes")
    back = pattern == NAMED["ping_pong"]
    e = edges.where("src != dst").select("eid", "src", "dst", "t")
    low, high = F.least("src", "dst"), F.greatest("src", "dst")
    e = e.withColumn("low", low).withColumn("high", high).withColumn("up", F.col("src") < F.col("dst"))
    near = Window.partitionBy("low", "high").orderBy("t").rangeBetween(-delta, 0)
    # those at the same time but of greater id come after, so they are taken off
    tie = Window.partitionBy("low", "high", "t").orderBy("eid").rowsBetween(0, Window.unboundedFollowing)
    up, down = F.col("up").cast("long"), (~F.col("up")).cast("long")
    wanted = F.when(F.col("up") == F.lit(not back), F.sum(up).over(near) - F.sum(up).over(tie)).otherwise(F.sum(down).over(near) - F.sum(down).over(tie))
    return e.withColumn("n", wanted).agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("count"))


def count_motifs(edges: DataFrame, pattern: Pattern, delta: int) -> DataFrame:
    """(count): pairs on two nodes by window, cyclic triangles by pairs within slices, the rest by the join chain with a partial count."""
    if canonical(pattern) in (NAMED["repeat"], NAMED["ping_pong"]):
        return count_pairs_by_window(edges, delta, pattern)
    if canonical(pattern) == NAMED["cyclic"]:
        return count_cycles(edges, delta)
    return motif_rows(edges, pattern, delta).agg(F.count(F.lit(1)).alias("count"))


def count_all_three_edge(edges: DataFrame, delta: int) -> DataFrame:
    """(pattern, count) of the 36 three-edge patterns, from two join chains for all: second and third edges classified by their ends."""
    width = max(1, delta)
    base = edges.where("src != dst").select("eid", "src", "dst", "t")
    both = F.explode(F.array(slice_of("t", width), slice_of("t", width) + 1))
    touching = base.select(F.col("eid").alias("e"), F.col("src").alias("s"), F.col("dst").alias("d"), "t", slice_of("t", width).alias("slice"), F.explode(F.array("src", "dst")).alias("node"))

    def extend(match: DataFrame, ends: list[str]) -> DataFrame:
        # an edge that touches two matched nodes is met twice; it counts at the first of them
        at = match.withColumn("node_at", F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.col(c).alias("node")) for i, c in enumerate(ends)])))
        joined = at.select("*", F.col("node_at.node").alias("node"), F.col("node_at.i").alias("i")).join(touching, ["node", "slice"])
        first = F.when((F.col(ends[0]) == F.col("s")) | (F.col(ends[0]) == F.col("d")), 0)
        for i, c in enumerate(ends[1:], 1):
            first = first.when((F.col(c) == F.col("s")) | (F.col(c) == F.col("d")), i)
        after = (F.col("t") > F.col("t_last")) | ((F.col("t") == F.col("t_last")) & (F.col("e") > F.col("e_last")))
        return joined.where(after & (F.col("t") - F.col("t0") <= delta) & (F.col("i") == first)).drop("node_at", "node", "i")

    def role(c: str, known: list[str]) -> Column:
        out = F.when(F.col(c) == F.col(known[0]), 0)
        for i, n in enumerate(known[1:], 1):
            out = out.when(F.col(c) == F.col(n), i)
        return out.otherwise(len(known))

    one = base.select(F.col("t").alias("t0"), F.col("t").alias("t_last"), F.col("eid").alias("e_last"), F.col("src").alias("n0"), F.col("dst").alias("n1"), both.alias("slice"))
    two = extend(one, ["n0", "n1"])
    ends = ["n0", "n1"]
    fresh = F.when(role("s", ends) == 2, F.col("s")).when(role("d", ends) == 2, F.col("d"))
    two = two.select("t0", "n0", "n1", fresh.alias("n2"), F.concat(role("s", ends), role("d", ends)).alias("second"), F.col("t").alias("t_last"), F.col("e").alias("e_last"), F.explode(F.array(slice_of("t0", width), slice_of("t0", width) + 1)).alias("slice"))
    # n2 is null until a third node is met, whatever numbers nodes have
    three = extend(two, ["n0", "n1", "n2"])
    r = lambda c: F.when(F.col(c) == F.col("n0"), 0).when(F.col(c) == F.col("n1"), 1).when(F.col("n2").isNull() | (F.col(c) == F.col("n2")), 2).otherwise(3)
    typed = three.select("second", F.concat(r("s"), r("d")).alias("third")).where("third not like '%3%'")
    return typed.groupBy(F.concat(F.lit("m"), "second", F.lit("_"), "third").alias("pattern")).agg(F.count(F.lit(1)).alias("count"))
