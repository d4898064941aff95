"""What plans run over: one state of a belief store, with maintained statistics so that checking a plan runs no job."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.canon import store_digest
from ..functions.timeaxis import DAY


@dataclass
class Stats:
    """Sizes that cost estimates use; approximate figures are allowed here and nowhere else."""

    edges: int = 0
    nodes: int = 0
    versions: int = 0
    idents: int = 0
    intervals: int = 0
    names: int = 0
    degree_high: int = 0
    t_min: int = 0
    t_max: int = 0
    per_day: dict[int, int] = field(default_factory=dict)

    def edges_between(self, t_from: int | None, t_to: int | None) -> int:
        lo = self.t_min if t_from is None else t_from
        hi = self.t_max + 1 if t_to is None else t_to
        return sum(n for day, n in self.per_day.items() if day + DAY > lo and day < hi)


def collect_stats(edges: DataFrame | None, versions: DataFrame | None, intervals: DataFrame | None = None, names: DataFrame | None = None) -> Stats:
    s = Stats()
    if edges is not None:
        days = {r["d"]: r["n"] for r in edges.groupBy((F.col("t") - F.pmod("t", F.lit(DAY))).alias("d")).agg(F.count(F.lit(1)).alias("n")).collect()}
        ends = edges.select(F.explode(F.array("src", "dst")).alias("node")).groupBy("node").agg(F.count(F.lit(1)).alias("n"))
        r = ends.agg(F.count(F.lit(1)).alias("nodes"), F.percentile_approx("n", 0.99).alias("high")).first()
        b = edges.agg(F.min("t"), F.max("t")).first()
        s.per_day, s.edges, s.nodes, s.degree_high, s.t_min, s.t_max = days, sum(days.values()), r["nodes"], r["high"] or 0, b[0] or 0, b[1] or 0
    if versions is not None:
        r = versions.agg(F.count(F.lit(1)), F.approx_count_distinct("ident")).first()
        s.versions, s.idents = r[0], r[1]
    s.intervals = intervals.count() if intervals is not None else 0
    s.names = names.count() if names is not None else 0
    return s


@dataclass
class Store:
    spark: SparkSession
    edges: DataFrame
    versions: DataFrame
    intervals: DataFrame | None = None
    names: DataFrame | None = None
    now_tt: int = 1 << 61
    ttl: int = 7 * DAY

    @cached_property
    def stats(self) -> Stats:
        return collect_stats(self.edges, self.versions, self.intervals, self.names)

    @cached_property
    def digest(self) -> str:
        return store_digest(self.edges.select("eid", "src", "dst", "t"))[:32] + store_digest(self.versions.select("ident", "vt_s", "vt_e", "tt_s", "w"))[:32]
