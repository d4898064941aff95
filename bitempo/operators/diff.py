"""What was added, removed and changed between two states."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.canon import canon_float
from ..functions.timeaxis import covers
from ..substrate.snapshots import scope


def _classified(paired: DataFrame, key: list[str]) -> DataFrame:
    change = F.when(F.col("n1") == 0, "added").when(F.col("n2") == 0, "removed").otherwise("changed")
    same = (F.col("n1") > 0) & (F.col("n2") > 0) & F.col("before").eqNullSafe(F.col("after"))
    return paired.where(((F.col("n1") > 0) | (F.col("n2") > 0)) & ~same).select(*key, change.alias("change"), "before", "after")


def _pair(df: DataFrame, key: list[str], in1: Column, in2: Column, value: Column) -> DataFrame:
    """One pass: disjointness leaves at most one version of a key in each state, so conditional aggregates pick it."""
    return df.where(in1 | in2).groupBy(*key).agg(
        F.max(F.when(in1, value)).alias("before"), F.max(F.when(in2, value)).alias("after"),
        F.count(F.when(in1, 1)).alias("n1"), F.count(F.when(in2, 1)).alias("n2"),
    )


def diff_states(versions: DataFrame, t1: int, t2: int, as_of_tt: int | None = None) -> DataFrame:
    """(ident, change, before, after) between two valid times of one belief state."""
    value = canon_float("w")
    held = scope(versions, as_of_tt)
    return _classified(_pair(held, ["ident"], covers("vt_s", "vt_e", F.lit(t1)), covers("vt_s", "vt_e", F.lit(t2)), value), ["ident"])


def diff_beliefs(versions: DataFrame, t: int, tt1: int, tt2: int) -> DataFrame:
    """(ident, change, before, after) between two belief states at one valid time."""
    at = versions.where(covers("vt_s", "vt_e", F.lit(t)))
    return _classified(_pair(at, ["ident"], covers("tt_s", "tt_e", F.lit(tt1)), covers("tt_s", "tt_e", F.lit(tt2)), canon_float("w")), ["ident"])


def diff_edges(edges: DataFrame, t1: int, t2: int, ttl: int) -> DataFrame:
    """(src, dst, change, before, after) of linked pairs, with the number of live edge events as their value."""
    live = lambda t: (F.col("t") <= t) & (F.col("t") > t - ttl)
    counted = edges.where(live(t1) | live(t2)).groupBy("src", "dst").agg(F.count(F.when(live(t1), 1)).alias("before"), F.count(F.when(live(t2), 1)).alias("after"))
    paired = counted.withColumns({"n1": F.col("before"), "n2": F.col("after")})
    return _classified(paired, ["src", "dst"])


def compose(first: DataFrame, second: DataFrame) -> DataFrame:
    """The change from 1 to 3 out of those from 1 to 2 and 2 to 3; equals the direct one."""
    a = first.select("ident", F.col("change").alias("c1"), F.col("before").alias("b1"), F.col("after").alias("a1"))
    b = second.select("ident", F.col("change").alias("c2"), F.col("before").alias("b2"), F.col("after").alias("a2"))
    both = a.join(b, "ident", "full_outer")
    was = F.when(F.col("c1").isNotNull(), F.col("c1") != "added").otherwise(F.col("c2") != "added")
    now = F.when(F.col("c2").isNotNull(), F.col("c2") != "removed").otherwise(F.col("c1") != "removed")
    before = F.when(F.col("c1").isNotNull(), F.col("b1")).otherwise(F.col("b2"))
    after = F.when(F.col("c2").isNotNull(), F.col("a2")).otherwise(F.col("a1"))
    rows = both.select("ident", was.alias("was"), now.alias("now"), before.alias("before"), after.alias("after"))
    change = F.when(~F.col("was"), "added").when(~F.col("now"), "removed").otherwise("changed")
    unchanged = F.col("was") & F.col("now") & F.col("before").eqNullSafe(F.col("after"))
    return rows.where((F.col("was") | F.col("now")) & ~unchanged).select("ident", change.alias("change"), "before", "after")
