"""Exact top-k inner products without random access.

Each component of the vectors is a sorted list; a query reads every list from the end that its own component favours. An object's
score is bounded from below by what was read of it and the far ends of its unread lists, from above by what was read and the
values just read there. Objects whose upper bound falls under the k-th lower bound are out; when few are left, their remaining
entries are read and their scores are final.

Lists are held for blocks of candidates, and a block is read in rounds of doubled depth for tiles of queries together: each bound of
all pairs after a round is a matrix product over what was read. The k-th score of earlier blocks of a task carries over, so later
blocks need upper bounds alone, begin at the depth where the block before them ended, and stop sooner. Entries below the depth are not
looked at until a pair survives; a block that is read to its end has exact scores. Queries go in groups of bounded number, one group after the other, and
only the group at hand is held by the driver and sent to all tasks; a tile and a block bound what a task holds.

Cases: vectors that are null, or hold a null or non-finite component, take no part; shorter vectors count as padded by zeros; ties
go to the lesser id; a query with fewer candidates has fewer results; rows with a query's own id are not its candidates; repeated
rows are separate candidates, and a repeated query row has results of its own; scores must fit a long and are exact whatever the components; rows with null ids take no part; an empty table gives an empty one; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import stash

K, SCALE, QUERIES_AT_ONCE, BLOCK, TILE, FEW = 5, 256, 20_000, 4096, 1024, 16


def usable(vector: Column) -> Column:
    bad = F.exists(vector, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return vector.isNotNull() & ~F.coalesce(bad, F.lit(False))


def quantized(vectors: list, width: int, scale: int = SCALE) -> np.ndarray:
    """floor(scale * x) of each component as whole numbers in doubles, padded to one width."""
    out = np.zeros((len(vectors), width))
    for i, v in enumerate(vectors):
        v = np.asarray(v, np.float64)[:width]
        out[i, : len(v)] = np.floor(scale * v)
    return out


def exact_kind(a: np.ndarray, b: np.ndarray) -> type:
    """A number type in which inner products of the two sets are exact."""
    most = float(np.abs(a).max(initial=0)) * float(np.abs(b).max(initial=0)) * max(1, a.shape[1])
    return np.float32 if most < 1 << 24 else np.float64 if most < 1 << 53 else object


def as_kind(a: np.ndarray, kind: type) -> np.ndarray:
    """The same whole numbers in another type; as objects they are Python's own, of any size."""
    if kind is not object:
        return a.astype(kind)
    out = np.empty(a.shape, object)
    out[...] = [[int(v) for v in row] for row in a]
    return out


class SortedLists:
    """The sorted lists of one block of candidates."""

    def __init__(self, vectors: np.ndarray, kind: type):
        self.x = as_kind(vectors, kind)
        self.n = len(vectors)
        self.sorted = np.sort(self.x, axis=0)
        self.rank = np.empty(vectors.shape, np.int32)
        np.put_along_axis(self.rank, np.argsort(self.x, axis=0, kind="stable"), np.arange(self.n, dtype=np.int32)[:, None], axis=0)

    def lower(self, up: np.ndarray, down: np.ndarray, depth: int) -> np.ndarray:
        """Lower bounds of all (query, object) pairs after ``depth`` entries of each list.

        ``up`` holds the queries' positive components, whose lists are read from the top, ``down`` the negative ones.
        """
        return up @ np.where(self.rank >= self.n - depth, self.x, self.sorted[0]).T + down @ np.where(self.rank < depth, self.x, self.sorted[-1]).T

    def upper(self, up: np.ndarray, down: np.ndarray, depth: int) -> np.ndarray:
        return up @ np.where(self.rank >= self.n - depth, self.x, self.sorted[self.n - depth]).T + down @ np.where(self.rank < depth, self.x, self.sorted[depth - 1]).T


def block_top_k(lists: SortedLists, ids: np.ndarray, queries: np.ndarray, query_ids: np.ndarray, k: int, floor: np.ndarray, begin: int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """(query place, candidate place, score) of the candidates of a block that may be among the queries' k best, and the depth that most queries needed.

    ``floor`` is the k-th score that each query has elsewhere already (-inf if none); ``begin`` is the first depth to read to.
    """
    x = lists.x
    queries = as_kind(queries, object if x.dtype == object else x.dtype.type)
    up, down = np.maximum(queries, 0), np.minimum(queries, 0)
    open_queries = np.arange(len(queries))
    out: list[tuple[np.ndarray, np.ndarray]] = []
    ended: dict[int, int] = {}
    depth = min(lists.n, max(1, begin or lists.n // 8))
    while len(open_queries):
        whole = depth >= lists.n
        upper = queries[open_queries] @ x.T if whole else lists.upper(up[open_queries], down[open_queries], depth)
        own = ids[None, :] == query_ids[open_queries][:, None]
        least = floor[open_queries]
        if lists.n >= k and (whole or not np.isfinite(least).all()):  # with a floor from elsewhere, upper bounds decide alone
            lower = upper.copy() if whole else lists.lower(up[open_queries], down[open_queries], depth)
            lower[own] = -np.inf
            best = np.sort(lower, axis=1) if lower.dtype == object else np.partition(lower, lists.n - k, axis=1)
            least = np.maximum(least, best[:, lists.n - k])
        alive = (upper >= least[:, None]) & ~own
        done = (alive.sum(axis=1) <= max(FEW, k)) | whole
        q, c = np.nonzero(alive[done])
        out.append((open_queries[done][q], c))
        ended[depth] = int(done.sum())
        open_queries = open_queries[~done]
        depth = min(lists.n, depth * 2)
    at, candidate = (np.concatenate(parts) for parts in zip(*out)) if out else (np.zeros(0, int), np.zeros(0, int))
    # the survivors' remaining entries
    scores = np.empty(len(at), object if x.dtype == object else np.float64)
    for s in range(0, len(at), 50_000):
        e = s + 50_000
        scores[s:e] = (queries[at[s:e]] * x[candidate[s:e]]).sum(axis=1)
    return at, candidate, scores, max(ended, key=lambda d: (ended[d], d), default=0)


class Best:
    """The k best of each query so far."""

    def __init__(self, queries: int, k: int):
        self.k = k
        self.rows = (np.zeros(0, int), np.zeros(0, np.int64), np.zeros(0))
        self.floor = np.full(queries, -np.inf)

    def add(self, at: np.ndarray, ids: np.ndarray, scores: np.ndarray) -> None:
        at, ids, scores = (np.concatenate(x) for x in zip(self.rows, (at, ids, scores)))
        if scores.dtype == object:
            order = np.array(sorted(range(len(at)), key=lambda i: (at[i], -scores[i], ids[i])), int)
        else:
            order = np.lexsort((ids, -scores, at))
        at, ids, scores = at[order], ids[order], scores[order]
        first = np.searchsorted(at, at)
        place = np.arange(len(at)) - first
        keep = place < self.k
        last = place == self.k - 1
        floor = scores[last].astype(np.float64)
        # rounding must not lift a floor above its score
        self.floor[at[last]] = np.nextafter(floor, -np.inf) if scores.dtype == object else floor
        self.rows = (at[keep], ids[keep], scores[keep])


def top_k(vectors: DataFrame, queries: DataFrame, k: int = K, at_once: int = QUERIES_AT_ONCE, block: int = BLOCK) -> DataFrame:
    """(query_id, rank, vec_id, score) for ``vectors(vec_id, embedding)`` and the query rows ``queries`` of the same shape."""
    spark = vectors.sparkSession
    ready = lambda df: df.select("vec_id", "embedding").where(F.col("vec_id").isNotNull() & usable(F.col("embedding")))
    vectors, queries = ready(vectors), ready(queries)
    measured = queries.agg(F.count(F.lit(1)), F.max(F.size("embedding"))).first()
    groups = max(1, -(-measured[0] // at_once))
    found = None
    for group in range(groups):
        rows = queries.where(F.pmod(F.xxhash64("vec_id"), F.lit(groups)) == group).orderBy("vec_id").toPandas()
        sent = spark.sparkContext.broadcast((rows["vec_id"].to_numpy(np.int64), quantized(rows["embedding"].tolist(), measured[1] or 0)))

        def search(batches: Iterator[pd.DataFrame], sent=sent, first=group << 32) -> Iterator[pd.DataFrame]:
            query_ids, q = sent.value
            tiles = [slice(s, s + TILE) for s in range(0, len(q), TILE)]
            best, begin = [Best(len(q[t]), k) for t in tiles], [0] * len(tiles)
            for batch in batches:
                for s in range(0, len(batch), block):
                    part = batch.iloc[s : s + block]
                    x, ids = quantized(part["embedding"].tolist(), q.shape[1]), part["vec_id"].to_numpy(np.int64)
                    if not len(q):
                        continue
                    lists = SortedLists(x, exact_kind(q, x))
                    for n, t in enumerate(tiles):
                        at, c, scores, begin[n] = block_top_k(lists, ids, q[t], query_ids[t], k, best[n].floor, begin[n])
                        best[n].add(at, ids[c], scores)
            for n, t in enumerate(tiles):
                at, ids, scores = best[n].rows
                yield pd.DataFrame({"query": first + t.start + at, "query_id": query_ids[t][at], "vec_id": ids, "score": [int(s) for s in scores]})

        part = stash(vectors.mapInPandas(search, "query long, query_id long, vec_id long, score long"), "best")
        sent.destroy()  # the group's results are stored, so the next group can take its place
        found = part if found is None else found.unionByName(part)
    rank = F.row_number().over(Window.partitionBy("query").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


#: The same search in DuckDB SQL.
ORACLE = f"""
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor({SCALE} * CAST(x AS DOUBLE)) AS BIGINT)) AS e FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
n AS (SELECT *, row_number() OVER () AS query FROM v WHERE vec_id % 50 = 0),
s AS (
  SELECT q.query, q.vec_id AS query_id, c.vec_id, CAST(list_sum(list_transform(list_zip(q.e, c.e), lambda z: z[1] * z[2])) AS BIGINT) AS score
  FROM n q JOIN v c ON q.vec_id != c.vec_id),
r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= {K}
"""
