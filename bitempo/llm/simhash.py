"""SimHash near-duplicates: whole-text fingerprints, linked at few differing bits through a byte-position index.

Two fingerprints of 64 bits that differ in at most ``bits`` = 2 places share at least 8 - 2 = 6 of their 8 positional bytes. The index
has a posting list for each choice of six positions and the bytes there (28 lists a fingerprint): a list of one position alone would hold a
256th of all fingerprints. Members of a list differ in the two positions left, so a list has 65,536 members at most, whatever the
corpus. In it each member looks up the members that are one or two bits away, which costs 136 looks and never pairs all with all.

A pair meets in as many lists as six positions can be chosen from the m bytes that it shares: once for m = 6, seven times for m = 7.
The lists that it was met in are counted, which gives m; pairs with m >= 6 are kept and verified by their differing bits.

Rows find their class by a join that is salted over the copies of a fingerprint, so a group of copies of any size is dealt over tasks.

Cases: null, empty and white-space texts have fingerprint zero and link like any other; texts of one or two words are
one shingle; repeated rows give repeated rows; rows with a null doc_id get the least doc_id of their class (null if it
has none); an empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations
from math import comb

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import stash
from .components import components

SHINGLE, SEED, BITS, SALTS = 3, 42, 2, 64
NO_ID = -(1 << 63)  # stands for a null id in joins; no document has it
_CHUNK = 1 << 15


def text_fingerprint(text: str | None, words: int = SHINGLE, seed: int = SEED) -> int:
    """Fingerprint of one text as an unsigned integer."""
    from xxhash import xxh64_intdigest

    # bytes.lower and bytes.split know ASCII letters and the six ASCII white-space bytes only, as the definition asks
    found = text.encode("utf-8", "surrogatepass").lower().split() if text else []
    if not found:
        return 0
    line = b" ".join(found)
    if len(found) <= words:
        spans = [(0, len(line))]
    else:
        lengths = np.fromiter(map(len, found), np.int64, len(found))
        ends = np.cumsum(lengths + 1) - 1
        spans = zip((ends - lengths)[: len(found) - words + 1].tolist(), ends[words - 1 :].tolist())
    hashes = np.fromiter((xxh64_intdigest(line[a:b], seed) for a, b in spans), np.uint64)
    ones = np.zeros(64, np.int64)
    for at in range(0, len(hashes), _CHUNK):
        part = hashes[at : at + _CHUNK]
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(hashes), bitorder="little").view("<u8")[0])


def fingerprint(text: Column) -> Column:
    """Fingerprint as a signed long with the same bits."""

    @F.pandas_udf("long")
    def of(texts: pd.Series) -> pd.Series:
        found = np.fromiter((text_fingerprint(t) for t in texts), np.uint64, len(texts))
        return pd.Series(found.view(np.int64))

    return of(text)


class Index:
    """Posting lists of fingerprints by the bytes at all but ``bits`` of their eight positions."""

    def __init__(self, bits: int = BITS):
        if bits not in (1, 2):
            raise ValueError("one or two differing bits")
        self.bits, self.rest = bits, 8 * bits
        self.choices = list(combinations(range(8), 8 - bits))
        self.left = [[p for p in range(8) if p not in c] for c in self.choices]
        one = [1 << b for b in range(self.rest)]
        self.flips = [*one, *[x | y for x, y in combinations(one, 2)]] if bits == 2 else one

    @staticmethod
    def _packed(fps: np.ndarray, positions) -> np.ndarray:
        out = np.zeros(len(fps), np.uint64)
        for k, p in enumerate(positions):
            out |= (fps >> np.uint64(8 * p) & np.uint64(255)) << np.uint64(8 * k)
        return out

    def postings(self, fps: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(list, what is left) of every fingerprint in every choice; a list's number holds the choice and its bytes."""
        kept = [self._packed(fps, c) | np.uint64(n << 8 * len(c)) for n, c in enumerate(self.choices)]
        return np.concatenate(kept).view(np.int64), np.concatenate([self._packed(fps, c) for c in self.left]).astype(np.int64)

    def fingerprints(self, lists: np.ndarray, left: np.ndarray) -> np.ndarray:
        """The fingerprints behind postings."""
        lists, left = lists.view(np.uint64), left.astype(np.uint64)
        out, choice = np.zeros(len(lists), np.uint64), (lists >> np.uint64(8 * (8 - self.bits))).astype(np.int64)
        for packed, table in ((lists, self.choices), (left, self.left)):
            places = np.array(table, np.uint64) * np.uint64(8)
            for k in range(places.shape[1]):
                out |= (packed >> np.uint64(8 * k) & np.uint64(255)) << places[choice, k]
        return out.view(np.int64)

    def near(self, lists: np.ndarray, left: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Pairs of members of one list within ``bits`` bits, from whole lists that are sorted by (list, what is left)."""
        same = lists[1:] == lists[:-1]
        member = np.concatenate([[False], same]) | np.concatenate([same, [False]]) if len(lists) else np.zeros(0, bool)
        lists, left = lists[member], left[member]
        if not len(lists):
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        number = np.cumsum(np.concatenate([[0], lists[1:] != lists[:-1]])) << self.rest
        at, ours, theirs = number | left, [], []
        for flip in self.flips:
            other = left ^ flip
            up = np.flatnonzero(other > left)
            wanted = number[up] | other[up]
            found = np.minimum(np.searchsorted(at, wanted), len(at) - 1)
            hit = at[found] == wanted
            ours.append(up[hit])
            theirs.append(found[hit])
        u, v = np.concatenate(ours), np.concatenate(theirs)
        return self.fingerprints(lists[u], left[u]), self.fingerprints(lists[v], left[v])


def fingerprint_links(prints: DataFrame, bits: int = BITS) -> DataFrame:
    """All pairs (u, v) of the distinct fingerprints ``prints(fp)`` that differ in at most ``bits`` bits."""
    index = Index(bits)

    def post(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            lists, left = index.postings(batch["fp"].to_numpy(np.int64).view(np.uint64))
            yield pd.DataFrame({"list": lists, "rest": left.astype(np.int32)})

    def meet(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        lists, left = np.zeros(0, np.int64), np.zeros(0, np.int64)
        for batch in batches:
            lists = np.concatenate([lists, batch["list"].to_numpy(np.int64)])
            left = np.concatenate([left, batch["rest"].to_numpy(np.int64)])
            whole = np.searchsorted(lists, lists[-1]) if len(lists) else 0  # the last list may go on in the next batch
            u, v = index.near(lists[:whole], left[:whole])
            lists, left = lists[whole:], left[whole:]
            yield pd.DataFrame({"u": u, "v": v})
        u, v = index.near(lists, left)
        yield pd.DataFrame({"u": u, "v": v})

    postings = prints.select("fp").mapInPandas(post, "list long, rest int").repartition("list").sortWithinPartitions("list", "rest")
    met = postings.mapInPandas(meet, "u long, v long").groupBy(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).agg(F.count(F.lit(1)).alias("lists"))
    shared = F.when(F.col("lists") >= comb(9 - bits, 8 - bits), 9 - bits).when(F.col("lists") >= 1, 8 - bits)
    return met.where((shared >= 8 - bits) & (F.bit_count(F.col("u").bitwiseXOR(F.col("v"))) <= bits)).select("u", "v")


def _prints(docs: DataFrame, *more: Column) -> DataFrame:
    """(doc_id, fp, salt, …) of every row; salts are stored, so that all who read them see the same."""
    return stash(docs.select("doc_id", fingerprint(F.col("text")).alias("fp"), *more).withColumn("salt", F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(SALTS)).cast("int")), "prints")


def _salted_join(rows: DataFrame, table: DataFrame, key: str) -> DataFrame:
    """Equi-join of ``rows(salt, …)`` with ``table``, which has one row for each key.

    A row of the table is repeated for the salts that its key's rows have: SALTS times at most, and never more often than there are rows.
    """
    return rows.join(rows.select(key, "salt").distinct().join(table, key), [key, "salt"])


def _classes(prints: DataFrame, bits: int) -> DataFrame:
    """(fp, component_id, root) for the distinct fingerprints of ``prints(doc_id, fp)``; root names the class by a fingerprint."""
    classes = stash(prints.groupBy("fp").agg(F.min("doc_id").alias("first")), "classes")
    linked = components(fingerprint_links(classes.select("fp"), bits)).withColumnRenamed("node", "fp")
    joined = stash(linked.join(classes, "fp").withColumn("salt", F.pmod(F.xxhash64("fp"), F.lit(SALTS)).cast("int")), "joined")
    least = stash(joined.groupBy("root").agg(F.min("first").alias("component_id")), "least")
    of_class = _salted_join(joined.select("fp", "root", "salt"), least, "root").select("fp", "component_id", "root")
    return classes.join(of_class, "fp", "left").select("fp", F.coalesce("component_id", "first").alias("component_id"), F.coalesce("root", "fp").alias("root"))


def near_duplicate_classes(docs: DataFrame, bits: int = BITS) -> DataFrame:
    """(doc_id, fp, component_id) for every row of ``docs(doc_id, text)``."""
    prints = _prints(docs)
    return _salted_join(prints, _classes(prints, bits).select("fp", "component_id"), "fp").select("doc_id", "fp", "component_id")


def one_of_each_class(docs: DataFrame, bits: int = BITS) -> DataFrame:
    """The rows of ``docs`` that represent their classes, with all columns: least doc_id (null last), then least fingerprint and text hash, one row of it."""
    key, body = F.coalesce("doc_id", F.lit(NO_ID)), F.coalesce(F.xxhash64("text"), F.lit(0))
    prints = _prints(docs, body.alias("body"))
    by_print = prints.groupBy("fp").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "body")).alias("first"))
    named = by_print.join(_classes(prints, bits).select("fp", "root"), "fp")
    kept = named.groupBy("root").agg(F.min(F.struct("first.none", "first.doc_id", "fp", "first.body")).alias("kept"))
    kept = stash(kept.select(F.coalesce("kept.doc_id", F.lit(NO_ID)).alias("kept_id"), F.coalesce("kept.body", F.lit(0)).alias("kept_body")), "kept")
    # one exchange of the texts: the aggregate that leaves one row keeps to the join's own keys, which are never null
    rows = docs.select(F.struct("*").alias("row"), key.alias("own_id"), body.alias("own_body"))
    chosen = kept.select(F.coalesce("kept_id", F.lit(NO_ID)).alias("kept_id"), F.coalesce("kept_body", F.lit(0)).alias("kept_body")).hint("merge")
    found = rows.join(chosen, (F.col("own_id") == F.col("kept_id")) & (F.col("own_body") == F.col("kept_body")))
    return found.dropDuplicates(["kept_id", "kept_body"]).select("row.*")


def hex_digits(fp: Column) -> Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))
