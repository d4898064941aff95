"""Counts of cyclic triangles a -> b -> c -> a without making an instance of them.

Edges are dealt over slices of time and counted there by pairs of nodes: what a task does grows with the edges of a pair times the triangles that
the pair lies in, not with the triples of edges, of which few nodes with many edges have the third power.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.timeaxis import HOUR
from .bandjoin import slice_of

#: Edges of triangles, or wedges, that a task looks at together.
BATCH = 1 << 19


def _spread(starts: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(owner, position) of the ranges [start, start + size), one after the other."""
    owner = np.repeat(np.arange(len(sizes)), sizes)
    return owner, np.arange(len(owner)) + np.repeat(starts - (np.cumsum(sizes) - sizes), sizes)


def _batches(sizes: np.ndarray) -> list[slice]:
    """Runs of items of about ``BATCH`` together; an item is never cut."""
    part = (np.cumsum(sizes) - sizes) // BATCH
    cuts = np.flatnonzero(np.diff(part)) + 1
    return [slice(a, b) for a, b in zip([0, *cuts], [*cuts, len(sizes)])] if len(sizes) else []


class _Slice:
    """Edges by pair, and in order of (t, eid) within a pair; equal (t, eid) have no order and take one place."""

    def __init__(self, eid: np.ndarray, src: np.ndarray, dst: np.ndarray, t: np.ndarray, end: int, delta: int):
        order = np.lexsort((eid, t))
        eid, src, dst, t = eid[order], src[order], dst[order], t[order]
        place = np.cumsum(np.concatenate(([False], (t[1:] != t[:-1]) | (eid[1:] != eid[:-1]))))
        horizon = place[np.searchsorted(t, t + delta, "right") - 1]  # the last place within delta of an edge
        nodes, ends = np.unique(np.concatenate((src, dst)), return_inverse=True)
        self.nodes = len(nodes)
        code = ends[: len(t)].astype(np.int64) * self.nodes + ends[len(t) :]
        by_pair = np.argsort(code, kind="stable")
        code, self.place, t = code[by_pair], place[by_pair], t[by_pair]
        self.codes, self.start, self.size = np.unique(code, return_index=True, return_counts=True)
        self.a, self.b = self.codes // self.nodes, self.codes % self.nodes
        pair = np.repeat(np.arange(len(self.codes)), self.size)
        self.places = int(place[-1]) + 1
        self.keys = pair * self.places + self.place
        own = t < end
        self.own = np.add.reduceat(own.astype(np.int64), self.start)
        # edges of one pair and time share their horizon, so first edges are taken in such runs
        first = np.flatnonzero(np.concatenate(([True], (pair[1:] != pair[:-1]) | (t[1:] != t[:-1]))))
        length = np.diff(np.append(first, len(t)))
        first, length = first[own[first]], length[own[first]]
        self.run_length, self.run_horizon = length, horizon[by_pair][first]
        self.run_at = first - self.start[pair[first]]
        self.run_start, self.runs = np.searchsorted(pair[first], np.arange(len(self.codes))), np.bincount(pair[first], minlength=len(self.codes))

    def upto(self, pair: np.ndarray, place: np.ndarray) -> np.ndarray:
        """Number of a pair's edges up to a place, that included."""
        return np.searchsorted(self.keys, pair * self.places + place, "right") - self.start[pair]

    def triangles(self):
        """(pq, qs, sp): pairs a -> b, b -> c, c -> a of each triangle once, in parts; wedges are made at the node of fewest pairs."""
        degree = np.bincount(self.a, minlength=self.nodes) + np.bincount(self.b, minlength=self.nodes)
        rank = np.empty(self.nodes, np.int64)
        rank[np.argsort(degree, kind="stable")] = np.arange(self.nodes)
        out = np.flatnonzero(rank[self.a] < rank[self.b])
        back = np.flatnonzero(rank[self.b] < rank[self.a])
        back = back[np.argsort(self.b[back], kind="stable")]
        apexes = self.b[back]
        lo, hi = np.searchsorted(apexes, self.a[out]), np.searchsorted(apexes, self.a[out], "right")
        for part in _batches(hi - lo):
            owner, at = _spread(lo[part], (hi - lo)[part])
            p, s = out[part][owner], back[at]
            wanted = self.b[p] * self.nodes + self.a[s]
            q = np.minimum(np.searchsorted(self.codes, wanted), len(self.codes) - 1)
            held = self.codes[q] == wanted
            yield p[held], q[held], s[held]

    def _links(self, x: np.ndarray, y: np.ndarray):
        """For each edge of ``x``, how many of ``y`` come up to its place; with running sums over each ``x``."""
        owner, at = _spread(self.start[x], self.size[x])
        seen = self.upto(y[owner], self.place[at])
        return owner, at - self.start[x][owner], seen, np.concatenate(([0], np.cumsum(seen))), np.cumsum(self.size[x]) - self.size[x]

    def count(self) -> int:
        total = 0
        for p, q, s in self.triangles():
            for part in _batches(self.size[p] + self.size[q] + self.size[s]):
                three = (p[part], q[part], s[part])
                links = [self._links(three[i], three[(i + 1) % 3]) for i in range(3)]
                # the first edge may lie in any of the three pairs
                total += sum(self._begun(three[i], three[(i + 1) % 3], three[(i + 2) % 3], links[i], links[(i + 1) % 3]) for i in range(3))
        return total

    def _begun(self, p: np.ndarray, q: np.ndarray, s: np.ndarray, pq, qs) -> int:
        """Triples whose first edge is of ``p``: second edges after it, times third edges up to its horizon, less those up to the second edge."""
        owner, at, seen, sums, base = pq
        _, _, _, after, after_base = qs
        run_owner, run = _spread(self.run_start[p], self.runs[p])
        last_q, last_s = self.upto(q[run_owner], self.run_horizon[run]), self.upto(s[run_owner], self.run_horizon[run])
        length, begin = self.run_length[run], base[run_owner] + self.run_at[run]
        zero = after_base[run_owner]
        found = (length * last_q - (sums[begin + length] - sums[begin])) * last_s - length * (after[zero + last_q] - after[zero])
        own = at < self.own[p][owner]
        zero = after_base[owner[own]]
        return int(found.sum()) + int((after[zero + seen[own]] - after[zero]).sum())


def count_cycles(edges: DataFrame, delta: int) -> DataFrame:
    """(count) of cyclic triangles in order of (t, eid), the last edge within ``delta`` of the first.

    A triangle counts in the slice of its first edge; a slice is four times as wide as ``delta`` (an hour at least), so of its edges those of the
    first ``delta`` alone go to the slice before, too.
    """
    width = max(4 * delta, HOUR)
    own = slice_of("t", width)
    slices = F.when(F.col("t") - own * width < delta, F.array(own, own - 1)).otherwise(F.array(own))
    dealt = edges.where("src != dst and t is not null").select("eid", "src", "dst", "t", F.explode(slices).alias("slice"))

    def counted(rows: pd.DataFrame) -> pd.DataFrame:
        end = (int(rows["slice"].iloc[0]) + 1) * width
        part = _Slice(*(rows[c].to_numpy() for c in ("eid", "src", "dst", "t")), end, delta)
        return pd.DataFrame({"count": [part.count()]})

    return dealt.groupBy("slice").applyInPandas(counted, "count long").agg(F.coalesce(F.sum("count"), F.lit(0)).alias("count"))
