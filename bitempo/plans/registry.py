"""One registry of operators: parameters, output fields, total orders, costs and how each runs. Tool schemas come from it."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.timeaxis import ALLEN, HOUR
from ..operators import compute as arithmetic
from ..operators import diff, evolution, history, intervals, motifs, neighbourhood, paths, reach, resolve, selection, series
from .store import Store


@dataclass(frozen=True)
class Param:
    kind: str  # integer, number, string, array, object, rows
    required: bool = False
    choices: tuple = ()
    least: int | None = None
    most: int | None = None
    role: str = ""  # ident (must be grounded), time, nodes (may be a whole step's rows)

    def schema(self) -> dict:
        out: dict = {"type": {"rows": "array"}.get(self.kind, self.kind)}
        if self.choices:
            out["enum"] = list(self.choices)
        if self.least is not None:
            out["minimum"] = self.least
        if self.most is not None:
            out["maximum"] = self.most
        return out


@dataclass(frozen=True)
class OperatorSpec:
    name: str
    about: str
    params: dict[str, Param]
    outputs: dict[str, str]
    order: tuple[str, ...]
    run: Callable[[Store, dict], DataFrame]
    common: dict[str, Param] = field(default_factory=lambda: {"as_of_tt": Param("integer", role="pin"), "limit": Param("integer", least=1, most=1000), "cursor": Param("string")})

    @property
    def all_params(self) -> dict[str, Param]:
        return {**self.params, **self.common}


PAGE_FIELDS = {"rows": "array", "rows_total": "integer", "rows_returned": "integer", "complete": "boolean", "cursor": "string", "result_digest": "string"}
REGISTRY: dict[str, OperatorSpec] = {}


def operator(name: str, about: str, params: dict[str, Param], outputs: dict[str, str], order: tuple[str, ...]):
    def keep(run):
        REGISTRY[name] = OperatorSpec(name, about, params, outputs, order, run)
        return run

    return keep


def edges_of(store: Store, args: dict) -> DataFrame:
    """Edges believed at the pin (those known by then), within the window, filter and node set of the arguments."""
    edges = store.edges
    if args.get("as_of_tt") is not None and "tt" in edges.columns:
        edges = edges.where(F.col("tt") <= args["as_of_tt"])
    elif args.get("as_of_tt") is not None:
        edges = edges.where(F.col("t") <= args["as_of_tt"])  # an event is known from its own time on
    edges = selection.select_edges(edges, selection.EdgeFilter.of(args.get("edges")))
    if args.get("nodes") is not None:
        edges = selection.restrict_nodes(edges, node_frame(store, args["nodes"]))
    return edges


def node_frame(store: Store, nodes) -> DataFrame:
    if isinstance(nodes, DataFrame):
        return nodes.toDF("node") if nodes.columns != ["node"] else nodes
    return store.spark.createDataFrame([(int(n),) for n in nodes], "node long")


INT, NUM, STR, ARR, OBJ = (Param(k) for k in ("integer", "number", "string", "array", "object"))
NEED = lambda kind, **k: Param(kind, True, **k)
WINDOW = {"t_from": NEED("integer", role="time"), "t_to": NEED("integer", role="time")}
SELECT = {"edges": OBJ, "nodes": Param("array", role="nodes")}


@operator("version_history", "Versions of one identity under a belief state.", {"ident": NEED("string", role="ident"), "audit": Param("boolean")}, {"ident": "string", "vt_s": "integer", "vt_e": "integer", "tt_s": "integer", "tt_e": "integer", "w": "number"}, ("vt_s", "tt_s"))
def _history(store, a):
    return history.version_history(store.versions, str(a["ident"]), a.get("as_of_tt"), bool(a.get("audit"))).select("ident", "vt_s", "vt_e", "tt_s", "tt_e", "w")


@operator("khop_neighbourhood", "Nodes within k hops in the snapshot at t.", {"seeds": NEED("array", role="nodes"), "k": NEED("integer", least=1, most=3), "t": NEED("integer", role="time"), "direction": Param("string", choices=("out", "in", "both")), "edges": OBJ}, {"node": "integer", "hop": "integer"}, ("hop", "node"))
def _khop(store, a):
    live = neighbourhood.snapshot_edges(edges_of(store, a), a["t"], store.ttl)
    return neighbourhood.khop_neighbourhood(live, node_frame(store, a["seeds"]), a["k"], a.get("direction", "out"))


@operator("diff_states", "Added, removed and changed identities between two valid times.", {"t1": NEED("integer", role="time"), "t2": NEED("integer", role="time")}, {"ident": "string", "change": "string", "before": "number", "after": "number"}, ("ident",))
def _diff(store, a):
    return diff.diff_states(store.versions, a["t1"], a["t2"], a.get("as_of_tt"))


@operator("earliest_arrival", "Earliest arrival over time-respecting paths.", {"sources": NEED("array", role="nodes"), **WINDOW, "max_wait": Param("integer", least=0), "min_wait": Param("integer", least=0), "max_hops": Param("integer", least=1), "targets": ARR, **SELECT}, {"source": "integer", "node": "integer", "arrival": "integer"}, ("arrival", "node", "source"))
def _reach(store, a):
    return reach.earliest_arrival(edges_of(store, a), node_frame(store, a["sources"]), a["t_from"], a["t_to"], a.get("max_wait"), a.get("min_wait", 0), max_hops=a.get("max_hops"), targets=a.get("targets"))


@operator("time_respecting_paths", "First node-simple paths between two nodes.", {"src": NEED("integer", role="ident"), "dst": NEED("integer", role="ident"), **WINDOW, "k": Param("integer", least=1, most=20), "max_hops": Param("integer", least=1, most=6), "max_wait": Param("integer", least=0), **SELECT}, {"rank": "integer", "nodes": "array", "eids": "array", "departs": "integer", "arrives": "integer", "hops": "integer"}, ("rank",))
def _paths(store, a):
    return paths.time_respecting_paths(edges_of(store, a), a["src"], a["dst"], a["t_from"], a["t_to"], a.get("k", 20), a.get("max_hops", 3), a.get("max_wait"))


def _pattern(a: dict) -> motifs.Pattern:
    given = a["pattern"]
    return motifs.NAMED[given] if isinstance(given, str) else tuple((int(x), int(y)) for x, y in given)


_MOTIF = {"pattern": NEED("string", choices=tuple(motifs.NAMED)), "delta": NEED("integer", least=1), "t_from": Param("integer", role="time"), "t_to": Param("integer", role="time"), **SELECT}


def _in_window(store: Store, a: dict) -> DataFrame:
    return selection.select_edges(edges_of(store, a), selection.EdgeFilter(t_from=a.get("t_from"), t_to=a.get("t_to")))


@operator("count_motifs", "Number of instances of a temporal motif.", _MOTIF, {"count": "integer"}, ("count",))
def _count(store, a):
    return motifs.count_motifs(_in_window(store, a), _pattern(a), a["delta"])


@operator("find_motifs", "Instances of a temporal motif.", _MOTIF, {"nodes": "array", "eids": "array", "t_first": "integer", "t_last": "integer"}, ("t_first", "eids"))
def _find(store, a):
    return motifs.motif_rows(_in_window(store, a), _pattern(a), a["delta"])


@operator("metric_series", "Bucketed statistics of the graph.", {**WINDOW, "width": NEED("integer", least=1), **SELECT}, {"bucket": "integer", "nodes": "integer", "edges": "integer", "deg_mean": "number", "deg_max": "integer", "reciprocity": "number"}, ("bucket",))
def _series(store, a):
    return series.metric_series(edges_of(store, a), a["t_from"], a["t_to"], a["width"])


@operator("detect_bursts", "Unusual buckets of the edge count.", {**WINDOW, "width": NEED("integer", least=1), "rule": NEED("string", choices=("zscore", "median")), "lookback": NEED("integer", least=2), "threshold": NEED("number"), "only_bursts": Param("boolean"), **SELECT}, {"bucket": "integer", "value": "number", "baseline": "number", "score": "number", "is_burst": "boolean"}, ("bucket",))
def _bursts(store, a):
    found = series.detect_bursts(series.event_counts(edges_of(store, a), a["t_from"], a["t_to"], a["width"]), a["rule"], a["lookback"], a["threshold"])
    return found.where("is_burst") if a.get("only_bursts") else found


@operator("neighbour_changes", "Neighbours gained, lost and kept between two windows.", {"node": NEED("integer", role="ident"), "w1": NEED("array"), "w2": NEED("array"), **SELECT}, {"neighbour": "integer", "change": "string"}, ("neighbour",))
def _evolve(store, a):
    return evolution.neighbour_changes(edges_of(store, a), a["node"], tuple(a["w1"]), tuple(a["w2"]))


@operator("interval_pairs", "Interval pairs of two selections in given relations.", {"a": NEED("object"), "b": NEED("object"), "relations": NEED("array"), "match": Param("string", choices=("src",))}, {"a_id": "integer", "b_id": "integer", "relation": "string"}, ("a_id", "b_id"))
def _pairs(store, a):
    held = store.intervals
    if a.get("as_of_tt") is not None:  # an interval is known from its transaction time, or its start, on
        held = held.where(F.col("tt" if "tt" in held.columns else "i_s") <= a["as_of_tt"])

    def side(f: dict) -> DataFrame:
        out = held
        for k, v in f.items():
            out = out.where(F.col(k) == v)
        return out

    return intervals.interval_pairs(side(a["a"]), side(a["b"]), tuple(a["relations"]), ("src",) if a.get("match") else (), HOUR)


@operator("resolve_names", "Identifiers of a name.", {"text": NEED("string", role="name"), "mode": Param("string", choices=resolve.MODES), "types": ARR}, {"ident": "integer", "type": "string", "name": "string", "score": "number", "ambiguous": "boolean"}, ("type", "ident"))
def _resolve(store, a):
    names = store.names
    if a.get("as_of_tt") is not None:  # a user is known from the first edge on; names of the fixed tables always are
        known = edges_of(store, {"as_of_tt": a["as_of_tt"]}).select(F.explode(F.array("src", "dst")).alias("ident")).distinct()
        names = names.where("type != 'user'").unionByName(names.where("type = 'user'").join(known, "ident", "left_semi"))
    return resolve.resolve_names(names, a["text"], a.get("mode", "folded"), a.get("types"))


@operator("compute", "Count, sum, extrema, top-k, filter or interval relation over an earlier step's rows.", {"fn": NEED("string", choices=arithmetic.FUNCTIONS), "input": NEED("rows", role="rows"), "field": STR, "k": Param("integer", least=1), "test": ARR, "ends": ARR, "relation": Param("string", choices=ALLEN)}, {"value": "number"}, ())
def _compute(store, a):
    return arithmetic.compute(a["input"], a["fn"], a.get("field"), a.get("k"), tuple(a["test"]) if a.get("test") else None, tuple(c for c in a["input"].columns if c != a.get("field"))[:3] if a["fn"] == "topk" else (), tuple(a["ends"]) if a.get("ends") else None, a.get("relation"))


def tool_manifest() -> list[dict]:
    """JSON Schemas of every operator's parameters and results."""
    return [
        {
            "name": s.name, "description": s.about,
            "parameters": {"type": "object", "properties": {k: p.schema() for k, p in s.all_params.items()}, "required": [k for k, p in s.params.items() if p.required], "additionalProperties": False},
            "returns": {"type": "object", "properties": {**{k: {"type": v} for k, v in PAGE_FIELDS.items()}, "rows": {"type": "array", "items": {"type": "object", "properties": {k: {"type": v} for k, v in s.outputs.items()}}}}},
        }
        for s in REGISTRY.values()
    ]


