"""Cross-entropy difference scores from matched n-gram models of a target and of the background.

Both models are of the same order over the same tokens: the lower-cased characters of the texts. Counts of 1- to 4-grams of both
lie in one stored table of exact n-grams, which grows with the corpus and is never gathered in one place. Background counts cover all
texts and are scaled to the number of target tokens, which makes the two models alike but for their texts. An n-gram's probability is
its count smoothed by that of the shorter n-gram. A document's score is the mean over its tokens of the target's loss less the
background's: the lower, the more like the target.

Texts are dealt by their ids into chunks of about ``CHUNK`` characters. A chunk's texts are counted together, and to be scored they
meet the counts of the n-grams that they hold, which come by a join of the chunks' n-grams with the table. What a task holds is
bounded by a chunk and what it holds n-grams for, whatever the corpus.

``Models`` is a form with a fixed number of hashed places for counts that must fit one process; no query uses it.

Cases: null and empty texts have no tokens and score 0; without a target text every score is 0; repeated rows count and
score each; texts of any length are read whole; ids that are null, or have no label, count for the background alone;
other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import stash

PLACES = (12, 16, 18, 20)  # log2 of the places for n-grams of 1, 2, 3, 4 characters
PRIOR = 4.0
CHUNK = 1 << 21
_CHARS = 1 << 20
_STEP, _SPREAD = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)
_OFFSETS = np.cumsum([0, *[1 << b for b in PLACES]])
SIZE = int(_OFFSETS[-1])


def packs(texts: list[str | None]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Texts in packs of about a million characters: places of their n-grams (4 rows), and each text's first and last column.

    Three columns of padding stand before each text.
    """
    held, chars = [], 0
    for text in texts:
        text = (text or "").lower().replace("\x00", "\x01")
        held.append(text)
        chars += len(text) + 3
        if chars >= _CHARS:
            yield _pack(held)
            held, chars = [], 0
    if held:
        yield _pack(held)


def _pack(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    line = np.frombuffer("".join(["\0\0\0" + t for t in texts]).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    ends = np.cumsum([len(t) + 3 for t in texts])
    spans = np.stack([np.concatenate([[0], ends[:-1]]) + 3, ends], axis=1)
    places = np.empty((len(PLACES), len(line)), np.int32)
    gram = np.zeros_like(line)
    for k, bits in enumerate(PLACES):
        before = np.zeros_like(gram)
        before[1:] = gram[:-1]
        gram = before * _STEP + line + np.uint64(1)
        mixed = gram * _SPREAD
        places[k] = ((mixed ^ (mixed >> np.uint64(32))) * _STEP) >> np.uint64(64 - bits)
        places[k] += int(_OFFSETS[k])
    return places, spans


def counted_places(places: np.ndarray, spans: np.ndarray) -> np.ndarray:
    """Places to count of a pack: all n-grams that end in a text, and the contexts of 1 to 3 paddings before it."""
    edges = np.zeros(places.shape[1] + 1, np.int32)
    np.add.at(edges, spans[:, 0], 1)
    np.add.at(edges, spans[:, 1], -1)
    inside = np.cumsum(edges[:-1]) > 0
    return np.concatenate([places[:, inside].ravel(), places[:3, spans[:, 0] - 1].ravel()])


def ngram_counts(docs: DataFrame) -> DataFrame:
    """(place, background, target) over all ``docs(text, is_target)``; at most ``SIZE`` rows."""

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        totals = np.zeros((2, SIZE), np.int64)
        for batch in batches:
            for aim in (False, True):
                for places, spans in packs(batch["text"][batch["is_target"] == aim].tolist()):
                    totals[int(aim)] += np.bincount(counted_places(places, spans), minlength=SIZE)
        totals[0] += totals[1]
        at = np.flatnonzero(totals[0])
        for s in range(0, len(at), 100_000):
            part = at[s : s + 100_000]
            yield pd.DataFrame({"place": part.astype(np.int32), "background": totals[0, part], "target": totals[1, part]})

    rows = docs.mapInPandas(count, "place int, background long, target long")
    return rows.groupBy("place").agg(F.sum("background").alias("background"), F.sum("target").alias("target"))


class Models:
    """The two models as count tables of one vocabulary."""

    def __init__(self, background: np.ndarray, target: np.ndarray):
        sizes = [c[: 1 << PLACES[0]].sum() for c in (background, target)]
        self.empty = not sizes[1]
        scale = sizes[1] / sizes[0] if sizes[0] else 0.0
        self.counts = [np.float32(target), np.float32(background * scale)]
        self.total = float(sizes[1])

    def losses(self, places: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Loss of every column under the target and the background, in nats."""
        out = []
        for counts in self.counts:
            p = (counts[places[0]] + np.float32(PRIOR / (1 << PLACES[0]))) / np.float32(self.total + PRIOR)
            for k in range(1, len(PLACES)):
                context = np.empty(places.shape[1], np.float32)
                context[0] = 0
                context[1:] = counts[places[k - 1][:-1]]
                p = (counts[places[k]] + np.float32(PRIOR) * p) / (context + np.float32(PRIOR))
            out.append(-np.log(np.minimum(p, 1)))
        return out[0], out[1]

    def score(self, texts: list[str | None]) -> list[tuple[int, float, float, float]]:
        """(tokens, target loss, background loss, difference) of each text, losses as means a token."""
        rows = []
        for places, spans in packs(texts):
            if self.empty:
                rows += [(int(b - a), 0.0, 0.0, 0.0) for a, b in spans]
                continue
            sums = [np.concatenate([[0.0], np.cumsum(x, dtype=np.float64)]) for x in self.losses(places)]
            n = spans[:, 1] - spans[:, 0]
            target, background = ((s[spans[:, 1]] - s[spans[:, 0]]) / np.maximum(n, 1) for s in sums)
            rows += list(zip(n.tolist(), target.tolist(), background.tolist(), (target - background).tolist()))
        return rows


class Grams:
    """The distinct 1- to 4-grams of some texts, and for each column of their line the numbers of those that end there.

    ``keys[k]`` are two numbers for each (k + 1)-gram that tell its characters: 21 bits a character, the last three in ``low``.
    """

    def __init__(self, texts: list[str | None]):
        texts = [(t or "").lower().replace("\x00", "\x01") for t in texts]
        line = np.frombuffer("".join(["\0\0\0" + t for t in texts]).encode("utf-32-le", "surrogatepass"), np.uint32)
        ends = np.cumsum([len(t) + 3 for t in texts], dtype=np.int64)
        self.starts, self.ends = np.concatenate([[0], ends[:-1]]) + 3, ends
        last, letters = pd.factorize(line.astype(np.int64))
        self.ids = [last]
        self.keys = [(np.zeros(len(letters), np.int64), letters + 1)]
        self.prefixes, self.suffixes = [np.zeros(len(letters), np.int64)], [np.zeros(len(letters), np.int64)]
        for _ in range(3):
            before = np.concatenate([[0], self.ids[-1][:-1]])  # the first column is padding, as is what stands before it
            own, pairs = pd.factorize(before * len(letters) + last)
            prefix, letter = pairs // len(letters), pairs % len(letters)
            suffix = np.empty(len(pairs), np.int64)
            suffix[own] = self.ids[-1]
            high, low = (x[prefix] for x in self.keys[-1])
            self.keys.append((high << 21 | low >> 42, (low & (1 << 42) - 1) << 21 | letters[letter] + 1))
            self.ids.append(own)
            self.prefixes.append(prefix)
            self.suffixes.append(suffix)

    def counts(self, chosen: np.ndarray) -> list[np.ndarray]:
        """How often each n-gram ends in one of the ``chosen`` texts, or is the padding before it."""
        edges = np.zeros(len(self.ids[0]) + 1, np.int32)
        np.add.at(edges, self.starts[chosen], 1)
        np.add.at(edges, self.ends[chosen], -1)
        inside = np.cumsum(edges[:-1]) > 0
        context = self.starts[chosen] - 1
        return [np.bincount(i[np.concatenate([np.flatnonzero(inside), context])] if k < 3 else i[inside], minlength=len(self.keys[k][0])) for k, i in enumerate(self.ids)]

    def losses(self, counts: list[np.ndarray], total: float, letters: int) -> np.ndarray:
        """Loss of each 4-gram's last character, in nats."""
        p = (counts[0] + PRIOR / letters) / (total + PRIOR)
        for k in range(1, 4):
            p = (counts[k] + PRIOR * p[self.suffixes[k]]) / (counts[k - 1][self.prefixes[k]] + PRIOR)
        return -np.log(np.minimum(p, 1))

    def means(self, losses: np.ndarray) -> np.ndarray:
        sums = np.concatenate([[0.0], np.cumsum(losses[self.ids[3]])])
        return (sums[self.ends] - sums[self.starts]) / np.maximum(self.ends - self.starts, 1)


@dataclass
class Table:
    """The two models as a stored table (high, low, background, target) of all n-grams."""

    counts: DataFrame
    letters: int
    background: int
    target: int
    docs: DataFrame  #: the counted texts
    chunks: int
    held: DataFrame  #: (chunk, high, low, …) of the counted texts


def _chunks(docs: DataFrame) -> int:
    return -(-(docs.agg(F.sum(F.length("text") + 3)).first()[0] or 1) // CHUNK)


def _chunk(chunks: int, *of: Column | str) -> Column:
    return F.pmod(F.xxhash64(*of), F.lit(chunks)).cast("long")


def _dealt(docs: DataFrame, chunks: int) -> DataFrame:
    # rows without an id have no label to meet and are dealt by their texts
    return docs.select(F.when(F.col("doc_id").isNull(), _chunk(chunks, "text")).otherwise(_chunk(chunks, "doc_id")).alias("chunk"), F.coalesce("doc_id", F.lit(0)).cast("long").alias("doc_id"), F.col("doc_id").isNull().alias("none"), "text")


def chunk_grams(docs: DataFrame, chosen: DataFrame, chunks: int) -> DataFrame:
    """(chunk, high, low, background, target) of the texts of each chunk; ``chosen(doc_id)`` are the ids of target texts."""

    def count(key: tuple, texts: pd.DataFrame, aims: pd.DataFrame) -> pd.DataFrame:
        names = ["chunk", "high", "low", "background", "target"]
        if not len(texts):
            return pd.DataFrame({n: np.zeros(0, np.int64) for n in names})
        grams = Grams(texts["text"].tolist())
        aim = (texts["doc_id"].isin(aims["doc_id"]) & ~texts["none"]).to_numpy() if len(aims) else np.zeros(len(texts), bool)  # an empty side has no columns
        every, target = grams.counts(np.ones(len(texts), bool)), grams.counts(aim)
        parts = [np.stack([np.full(len(n), key[0]), *grams.keys[k], n, target[k]])[:, n > 0] for k, n in enumerate(every)]
        return pd.DataFrame(np.concatenate(parts, axis=1).T, columns=names)

    marks = chosen.select(_chunk(chunks, "doc_id").alias("chunk"), "doc_id")
    return _dealt(docs, chunks).groupBy("chunk").cogroup(marks.groupBy("chunk")).applyInPandas(count, "chunk long, high long, low long, background long, target long")


def train(docs: DataFrame, target: DataFrame) -> Table:
    """Models of ``docs(doc_id, text)``; the target texts are those whose ids ``target(doc_id)`` holds."""
    chosen = target.where(F.col("doc_id").isNotNull()).select("doc_id").distinct()
    chunks = _chunks(docs)
    held = stash(chunk_grams(docs, chosen, chunks), "grams")
    counts = stash(held.groupBy("high", "low").agg(F.sum("background").alias("background"), F.sum("target").alias("target")), "counts")
    letters, background, aims = counts.where(F.col("high") + F.shiftright("low", 21) == 0).agg(F.count(F.lit(1)), F.sum("background"), F.sum("target")).first()
    return Table(counts, letters, background or 0, aims or 0, docs, chunks, held)


def scored(docs: DataFrame, models: Table) -> DataFrame:
    """(doc_id, n_tokens, target_loss, background_loss, score) for every row of ``docs(doc_id, text)``."""
    if docs is models.docs:
        chunks, held = models.chunks, models.held
    else:
        chunks = _chunks(docs)
        held = chunk_grams(docs, docs.select("doc_id").limit(0), chunks)
    # n-grams meet their counts by a shuffle at every size: neither side is bounded
    known = held.select("chunk", "high", "low").join(models.counts.hint("merge"), ["high", "low"])
    letters, total, scale = models.letters, float(models.target), models.target / models.background if models.background else 0.0

    def score(key: tuple, texts: pd.DataFrame, known: pd.DataFrame) -> pd.DataFrame:
        if not len(texts):  # an empty side has no columns
            return pd.DataFrame({n: [] for n in ("doc_id", "n_tokens", "target_loss", "background_loss", "score")})
        grams = Grams(texts["text"].tolist())
        out = pd.DataFrame({"doc_id": texts["doc_id"].astype("Int64").mask(texts["none"]), "n_tokens": grams.ends - grams.starts, "target_loss": 0.0, "background_loss": 0.0})
        if total:
            found = []
            for high, low in grams.keys:
                rows = pd.DataFrame({"high": high, "low": low}).merge(known, "left", ["high", "low"])
                found.append(rows[["background", "target"]].fillna(0).to_numpy(np.float64))
            out["target_loss"] = grams.means(grams.losses([x[:, 1] for x in found], total, letters))
            out["background_loss"] = grams.means(grams.losses([x[:, 0] * scale for x in found], total, letters))
        return out.assign(score=out["target_loss"] - out["background_loss"])

    pairs = _dealt(docs, chunks).groupBy("chunk").cogroup(known.select("chunk", "high", "low", "background", "target").groupBy("chunk"))
    return pairs.applyInPandas(score, "doc_id long, n_tokens long, target_loss double, background_loss double, score double")
