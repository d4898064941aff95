"""Baselines that see the latest state alone: a two-hop context, and pattern queries over the present graph."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.timeaxis import OPEN_END
from ..operators.neighbourhood import khop_neighbourhood
from ..plans.store import Store


def latest_edges(edges: DataFrame, ttl: int) -> DataFrame:
    """(src, dst) live at the last event, without times."""
    last = edges.agg(F.max("t")).first()[0] or 0
    return edges.where((F.col("t") <= last) & (F.col("t") > last - ttl)).select("src", "dst").distinct()


def latest_two_hop(edges: DataFrame, seeds: list[int], ttl: int) -> DataFrame:
    """(src, dst) among the nodes within two hops of the seeds in the latest snapshot."""
    live = latest_edges(edges, ttl)
    start = edges.sparkSession.createDataFrame([(s,) for s in seeds], "node long")
    near = khop_neighbourhood(live, start, 2, "both").select("node")
    return live.join(near.withColumnRenamed("node", "src"), "src", "left_semi").join(near.withColumnRenamed("node", "dst"), "dst", "left_semi").select("src", "dst")


class LatestTwoHop:
    """Reads counts and neighbours off the latest two-hop context; knows no times and no beliefs."""

    def __init__(self, store: Store):
        self.store = store

    def __call__(self, task) -> object:
        if task.template not in ("a03", "e01"):
            return None
        u = task.needs["u"]
        rows = latest_two_hop(self.store.edges, [u], self.store.ttl).collect()
        if task.template == "a03":
            return len({x for r in rows for x in (r["src"], r["dst"])} | {u})
        return sorted(str(r["dst"]) for r in rows if r["src"] == u) or None


@dataclass(frozen=True)
class Match:
    """A chain of edges ``(a)-[..]->(b)-[..]->(c)``, tests on properties, and one aggregate of what matches.

    ``links``: pairs of names; ``where``: (name or "e0", property, test, value) with e0 the first edge; ``give``: ("count", None) or (fn, "e0.w").
    """

    links: tuple[tuple[str, str], ...]
    where: tuple[tuple[str, str, str, object], ...] = ()
    give: tuple[str, str | None] = ("count", None)


def run_latest_pattern(query: Match, edges: DataFrame) -> DataFrame:
    """(value) of a pattern over edges (src, dst, t, w); self-joins that the planner orders."""
    out, bound = None, set()
    for i, (a, b) in enumerate(query.links):
        e = edges.select(*[F.col(c).alias(f"e{i}.{c}") for c in ("eid", "src", "dst", "t", "w")])
        if out is None:
            out = e.withColumns({a: F.col(f"`e{i}.src`"), b: F.col(f"`e{i}.dst`")})
        else:
            on = [F.col(n) == F.col(f"`e{i}.{side}`") for n, side in ((a, "src"), (b, "dst")) if n in bound]
            test = on[0]
            for extra in on[1:]:
                test = test & extra
            out = out.join(e, test)
            out = out.withColumns({n: F.col(f"`e{i}.{side}`") for n, side in ((a, "src"), (b, "dst")) if n not in bound})
            for j in range(i):
                out = out.where(F.col(f"`e{i}.eid`") != F.col(f"`e{j}.eid`"))
        bound |= {a, b}
    tests = {"=": lambda c, v: c == v, "<": lambda c, v: c < v, "<=": lambda c, v: c <= v, ">": lambda c, v: c > v, ">=": lambda c, v: c >= v}
    for name, prop, test, value in query.where:
        out = out.where(tests[test](F.col(name) if prop == "id" else F.col(f"`{name}.{prop}`"), value))
    fn, what = query.give
    return out.agg((F.count(F.lit(1)) if fn == "count" else getattr(F, fn)(F.col(f"`{what}`"))).alias("value"))


class LatestPattern:
    """An exact query engine over the latest state: time is a property, what was believed before is gone."""

    def __init__(self, store: Store):
        self.store = store

    def __call__(self, task) -> object:
        s, p = self.store, task.needs
        if task.template == "a01":
            now = s.versions.where((F.col("ident") == str(p["u"])) & (F.col("tt_e") == OPEN_END) & (F.col("vt_s") <= p["d"]) & (F.col("vt_e") > p["d"]))
            row = now.select("w").first()
            # a question about an earlier belief has no answer in this state; answering with the present one would be a guess
            return row[0] if row and task.probe_side != "before" else None
        if task.template == "e01":
            rows = s.edges.where((F.col("src") == p["u"]) & (F.col("t") >= p["d"]) & (F.col("t") < p["d"] + 3 * 86_400_000_000)).select("dst").distinct().collect()
            return sorted(str(r[0]) for r in rows) or None
        if task.template == "a02":
            return s.versions.where((F.col("ident") == str(p["u"])) & (F.col("tt_e") == OPEN_END)).count() or None
        return None
