"""Best-fit packing of token pieces into sequences, improved by swaps between underfull sequences.

Documents are tokenized once, each closed by an end id, and cut only where one is longer than a sequence. Full pieces are
sequences of their own. The rest is dealt evenly into pools of about ``pool`` pieces, one task each: pieces go, longest
first, to the fullest bin that holds them; then local search moves one document, or exchanges one for one, two for one or one for two,
between any two underfull bins, whenever that increases the sum of squared fills, until no exchange does. Partners are looked up
by the lengths that one or two of their pieces have together. Bins that empty go.

Cases: a null or empty text is its end id alone; repeated rows are packed once for each row; null doc_ids are kept; an empty
table gives no rows; other columns are ignored. A pool's size bounds a task's memory whatever the table's size, and costs at most
about one sequence a pool.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from heapq import heappop, heappush

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import crc_of_ids, default_vocabulary, stash, word_tokenizer

LENGTH, POOL = 2048, 40_000


def token_pieces(docs: DataFrame, vocabulary: str | None = None, end_id: int = 0, length: int = LENGTH, keep_ids: bool = False) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32[, ids]) for ``docs(doc_id, text)``."""
    vocabulary = vocabulary or default_vocabulary()

    def cut_up(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        tokens = word_tokenizer(vocabulary)
        end = np.array([end_id], tokens.kind)
        for batch in batches:
            rows, texts = [], batch["text"].tolist()
            for doc_id, encoded in zip(batch["doc_id"].astype("object").tolist(), tokens.encode(texts)):
                ids = np.concatenate([encoded, end])
                for piece, start in enumerate(range(0, len(ids), length)):
                    part = ids[start : start + length]
                    rows.append((doc_id, piece, start, len(part), crc_of_ids(part), *([part.tolist()] if keep_ids else [])))
            names = ["doc_id", "piece", "start", "length", "ids_crc32", *(["ids"] if keep_ids else [])]
            yield pd.DataFrame(rows, columns=names).astype({"doc_id": "Int64"})

    shape = "doc_id long, piece int, start long, length long, ids_crc32 long" + ", ids array<int>" * keep_ids
    return docs.select("doc_id", "text").mapInPandas(cut_up, shape)


class Bins:
    """Bins of one pool: items are lengths, bins hold item numbers."""

    def __init__(self, lengths: list[int], size: int):
        self.lengths, self.size = lengths, size
        self.held: list[list[int]] = []
        self.fill: list[int] = []

    def best_fit(self) -> None:
        """Longest first, each into the bin with the least room that suffices."""
        by_room: list[list[int]] = [[] for _ in range(self.size + 1)]
        rooms = 0  # bit r is set if some bin has room r
        for item in sorted(range(len(self.lengths)), key=lambda i: (-self.lengths[i], i)):
            n = self.lengths[item]
            fitting = rooms >> n
            if fitting:
                room = n + (fitting & -fitting).bit_length() - 1
                at = by_room[room].pop()
                if not by_room[room]:
                    rooms &= ~(1 << room)
                self.held[at].append(item)
                self.fill[at] += n
            else:
                at, room = len(self.held), self.size
                self.held.append([item])
                self.fill.append(n)
            room -= n
            if room:
                by_room[room].append(at)
                rooms |= 1 << room

    def improve(self) -> int:
        """Local search between underfull bins; returns the number of exchanges made.

        The fullest bins take first, each from the least filled bin that fills it most, until a whole sweep makes no exchange.
        Each exchange raises the sum of squared fills, so the search ends.
        """
        givers, made = Givers(self.size), 0
        under = [b for b in range(len(self.held)) if self.held[b] and self.fill[b] < self.size]
        for b in under:
            self._offer(givers, b)
        before = -1
        while made != before:
            before = made
            under = sorted((b for b in under if self.held[b] and self.fill[b] < self.size), key=lambda b: (-self.fill[b], b))
            for taker in under:
                while self.held[taker] and self.fill[taker] < self.size and self._take(givers, taker):
                    made += 1
        self.held, self.fill = zip(*[(h, f) for h, f in zip(self.held, self.fill) if h]) if any(self.held) else ((), ())
        return made

    def _offer(self, givers: Givers, b: int) -> None:
        if self.held[b] and self.fill[b] < self.size:
            givers.add(b, self.fill[b], [self.lengths[i] for i in self.held[b]])
        else:
            givers.drop(b)

    def _take(self, givers: Givers, taker: int) -> bool:
        """The exchange that fills ``taker`` most, if one raises the sum of squared fills."""
        found = givers.best(taker, self.fill[taker])
        if found is None:
            return False
        giver, gain, count, back = found
        out = self._pick(giver, count, gain + back)
        back_items = next(p for n in (0, 1, 2) if (p := self._pick(taker, n, back)) is not None)
        self.held[giver] = [i for i in self.held[giver] if i not in out] + back_items
        self.held[taker] = [i for i in self.held[taker] if i not in back_items] + out
        self.fill[giver] -= gain
        self.fill[taker] += gain
        self._offer(givers, giver)
        self._offer(givers, taker)
        return True

    def _pick(self, b: int, count: int, total: int) -> list[int] | None:
        """``count`` items of a bin that have ``total`` together."""
        if count == 0:
            return [] if total == 0 else None
        seen: dict[int, int] = {}
        for i in self.held[b]:
            n = self.lengths[i]
            if count == 1 and n == total:
                return [i]
            if count == 2 and total - n in seen:
                return [seen[total - n], i]
            seen[n] = i
        return None


class Givers:
    """Underfull bins by what one or two of their pieces have together, the least filled first."""

    def __init__(self, size: int):
        self.size = size
        self.least = np.full((3, size + 1), 2 * size + 1)  # the least fill of a bin with one or two pieces of a length
        self.heaps: dict[tuple[int, int], list[tuple[int, int, int]]] = {}
        self.stamp: dict[int, int] = {}
        self.sums: dict[int, tuple[list[int], list[int]]] = {}

    def _keys(self, b: int) -> list[tuple[int, int]]:
        one, two = self.sums.get(b, ((), ()))
        return [*[(1, n) for n in one], *[(2, n) for n in two]]

    def _refresh(self, key: tuple[int, int]) -> None:
        heap = self.heaps[key]
        while heap and self.stamp[heap[0][1]] != heap[0][2]:
            heappop(heap)
        self.least[key] = heap[0][0] if heap else 2 * self.size + 1

    def drop(self, b: int) -> None:
        self.stamp[b] = self.stamp.get(b, 0) + 1
        for key in self._keys(b):
            self._refresh(key)
        self.sums.pop(b, None)

    def add(self, b: int, fill: int, lengths: list[int]) -> None:
        self.drop(b)
        own = Counter(lengths)
        one = sorted(own)
        self.sums[b] = one, sorted({x + y for i, x in enumerate(one) for y in one[i + (own[x] < 2) :]})
        for key in self._keys(b):
            heap = self.heaps.setdefault(key, [])
            heappush(heap, (fill, b, self.stamp[b]))
            self._refresh(key)

    def best(self, taker: int, fill: int) -> tuple[int, int, int, int] | None:
        """(giver, gain, pieces it gives, length it gets back) of the greatest gain; one for none, one or two, or two for one."""
        aside = []
        for key in self._keys(taker):  # a bin is no partner of its own
            heap = self.heaps[key]
            if heap[0][1] == taker:
                aside.append((key, heappop(heap)))
                self._refresh(key)
        one, two = self.sums[taker]
        gains = np.arange(1, self.size - fill + 1)
        found = None
        for count, backs in ((1, np.array([0, *one, *two])), (2, np.array(one))):
            # the taker must come out fuller than the giver was
            rises = self.least[count][backs[:, None] + gains] < fill + gains
            columns = np.flatnonzero(rises.any(axis=0))
            if len(columns) and (found is None or gains[columns[-1]] > found[1]):
                gain = int(gains[columns[-1]])
                fits = np.flatnonzero(rises[:, columns[-1]])
                back = int(backs[fits[np.argmin(self.least[count][backs[fits] + gain])]])
                found = self.heaps[count, back + gain][0][1], gain, count, back
        for key, entry in aside:
            heappush(self.heaps[key], entry)
            self._refresh(key)
        return found


def pack_lengths(lengths: list[int], size: int = LENGTH) -> list[list[int]]:
    """Bins of item numbers for one pool."""
    bins = Bins([int(n) for n in lengths], size)
    bins.best_fit()
    bins.improve()
    return [list(h) for h in bins.held]


def pack_pieces(pieces: DataFrame, size: int = LENGTH, pool: int = POOL) -> DataFrame:
    """Add ``sequence_id`` and ``offset`` to ``pieces(…, length)``; the pieces must be stored, since they are read twice."""
    shape = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pieces.schema) + ", sequence_id long, offset long"
    whole = pieces.where(F.col("length") >= size).withColumn("sequence_id", -1 - F.monotonically_increasing_id()).withColumn("offset", F.lit(0).cast("long"))
    part = pieces.where(F.col("length") < size)
    pools = max(1, -(-part.count() // pool))

    def pack(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyspark import TaskContext

        first = TaskContext.get().partitionId() << 32
        frames = [b for b in batches if len(b)]
        if not frames:
            return
        held = pd.concat(frames, ignore_index=True)
        sequence, offset = np.zeros(len(held), np.int64), np.zeros(len(held), np.int64)
        lengths = held["length"].to_numpy()
        for n, items in enumerate(pack_lengths(lengths.tolist(), size)):
            at = np.array(items)
            sequence[at] = first + n
            offset[at] = np.cumsum(lengths[at]) - lengths[at]
        yield held.assign(sequence_id=sequence, offset=offset).astype({"doc_id": "Int64"})

    return whole.unionByName(part.repartition(pools).mapInPandas(pack, shape))


def packed(docs: DataFrame, vocabulary: str | None = None, end_id: int = 0, length: int = LENGTH, pool: int = POOL, keep_ids: bool = False) -> DataFrame:
    return pack_pieces(stash(token_pieces(docs, vocabulary, end_id, length, keep_ids), "pieces"), length, pool)
