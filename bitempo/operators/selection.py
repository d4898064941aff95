"""Edge selections: conjunctive filters that reach the scan."""

from __future__ import annotations

from dataclasses import dataclass, fields

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class EdgeFilter:
    etype: str | None = None
    src: int | None = None
    dst: int | None = None
    w_min: float | None = None
    w_max: float | None = None
    t_from: int | None = None
    t_to: int | None = None

    @classmethod
    def of(cls, given: dict | None) -> "EdgeFilter":
        return cls(**{k: v for k, v in (given or {}).items() if k in {f.name for f in fields(cls)}})


def select_edges(edges: DataFrame, f: EdgeFilter) -> DataFrame:
    for name in ("etype", "src", "dst"):
        if getattr(f, name) is not None:
            edges = edges.where(F.col(name) == getattr(f, name))
    if f.w_min is not None:
        edges = edges.where(F.col("w") >= f.w_min)
    if f.w_max is not None:
        edges = edges.where(F.col("w") <= f.w_max)
    if f.t_from is not None:
        edges = edges.where(F.col("t") >= f.t_from)
    if f.t_to is not None:
        edges = edges.where(F.col("t") < f.t_to)
    return edges


def restrict_nodes(edges: DataFrame, nodes: DataFrame, both: bool = True) -> DataFrame:
    """Edges whose source (and destination) is among ``nodes(node)``; the planner broadcasts the nodes where they are few."""
    out = edges.join(nodes.select(F.col("node").alias("src")).distinct(), "src", "left_semi")
    return out.join(nodes.select(F.col("node").alias("dst")).distinct(), "dst", "left_semi").select(*edges.columns) if both else out
