"""Language ID by rank-order profiles: out-of-place distance of a text's most frequent n-grams to each language's.

A profile holds the ``top`` most frequent letter n-grams (n = 1 to 3, words padded by a space) of a language's training
texts. A text's own ``top`` n-grams are ranked alike; each adds the difference of its two ranks, or ``top`` where
the profile lacks it. The language of least distance wins, ties go to the lesser code.

Cases: null texts and texts without a letter (Unicode category L; fractions, superscripts and circled numbers are none) are ``und`` with score 0; with no training row every text is ``und``;
ties of counts are ranked by the n-gram's code points; repeated rows get equal results; very long texts are counted
whole; other columns are ignored. The training sample is bounded by ``per_language`` texts of each language (chosen by
a hash of the id); whatever is predicted is predicted from the whole text.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

TOP = 400
PER_LANGUAGE = 4000
UNKNOWN = "und"
_WORD = re.compile(r"[^\W\d_]+")  # letters, and numbers that are not decimal digits


def letter_words(text: str) -> Counter[str]:
    """Counts of the runs of letters (Unicode category L) of a lower-cased text."""
    words = Counter(_WORD.findall(text))
    for word in [w for w in words if not w.isalpha()]:
        n = words.pop(word)
        for part in "".join([c if c.isalpha() else " " for c in word]).split():
            words[part] += n
    return words


class GramCounter:
    """n-gram counts of whole texts; n-grams get local numbers, words remember the numbers of their n-grams."""

    def __init__(self, most_grams: int = 200_000, most_words: int = 200_000):
        self.most_grams, self.most_words, self.generation = most_grams, most_words, 0
        self.clear()

    def clear(self) -> None:
        self.generation += 1
        self.number: dict[str, int] = {}
        self.grams: list[str] = []
        self.codes = np.zeros(0, np.int64)
        self.of_word: dict[str, np.ndarray] = {}

    def _word(self, word: str) -> np.ndarray:
        padded = f" {word} "
        size = len(padded)
        number, found = self.number, []
        for gram in [*word, *[padded[i : i + 2] for i in range(size - 1)], *[padded[i : i + 3] for i in range(size - 2)]]:
            at = number.get(gram)
            if at is None:
                at = number[gram] = len(self.grams)
                self.grams.append(gram)
            found.append(at)
        return np.array(found, np.int64)

    def ranked(self, text: str, top: int) -> tuple[np.ndarray, np.ndarray]:
        """Numbers and counts of the text's most frequent n-grams, most frequent first; empty if it has no letter."""
        words = letter_words(text.lower())
        if not words:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        if len(self.grams) > self.most_grams or len(self.of_word) > self.most_words:
            self.clear()
        known, parts = self.of_word, []
        for word in words:
            part = known.get(word)
            if part is None:
                part = self._word(word)
                if len(word) <= 40:
                    known[word] = part
            parts.append(part)
        times = np.repeat(np.fromiter(words.values(), np.int64, len(words)), np.fromiter(map(len, parts), np.int64, len(parts)))
        counts = np.bincount(np.concatenate(parts), times, len(self.grams))
        held = np.flatnonzero(counts)
        n = counts[held].astype(np.int64)
        if len(self.codes) < len(self.grams):
            new = self.grams[len(self.codes) :]
            self.codes = np.concatenate([self.codes, np.array([_code(g) for g in new], np.int64)])
        order = np.lexsort((self.codes[held], -n))[:top]
        return held[order], n[order]


def _code(gram: str) -> int:
    """A number that orders n-grams of up to three characters by their code points."""
    at = [ord(c) + 1 for c in gram] + [0, 0]
    return (at[0] << 42) | (at[1] << 21) | at[2]


def train(docs: DataFrame, top: int = TOP, per_language: int = PER_LANGUAGE) -> dict[str, list[str]]:
    """Profiles {language: n-grams, most frequent first} from ``docs(doc_id, text, lang)``."""
    known = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull())
    sizes = {r["lang"]: r["n"] for r in known.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not sizes:
        return {}
    # a bounded sample: each language keeps the share of ids that leaves about per_language of them
    share = F.element_at(F.create_map(*[x for lang, n in sizes.items() for x in (F.lit(lang), F.lit(min(1.0, per_language / n)))]), F.col("lang"))
    sample = known.where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < share * 1_000_000).select("text", "lang")

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        counter, held = GramCounter(), {}
        for batch in batches:
            for text, lang in zip(batch["text"], batch["lang"]):
                numbers, counts = counter.ranked(text, 1 << 30)
                total = held.setdefault(lang, Counter())
                for at, n in zip(numbers.tolist(), counts.tolist()):
                    total[counter.grams[at]] += n
        for lang, total in held.items():
            if not total:
                continue
            yield pd.DataFrame({"lang": [lang] * len(total), "gram": list(total), "n": list(total.values())})

    counts = sample.mapInPandas(count, "lang string, gram string, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    # top n-grams of each language, gathered in an aggregate of bounded size
    from pyspark.sql import Window

    place = F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "gram"))
    rows = counts.withColumn("place", place).where(F.col("place") <= top).orderBy("lang", "place").collect()
    profiles: dict[str, list[str]] = {}
    for r in rows:
        profiles.setdefault(r["lang"], []).append(r["gram"])
    return profiles


class Identifier:
    def __init__(self, profiles: dict[str, list[str]], top: int = TOP):
        self.top, self.profiles = top, profiles
        self.languages = sorted(profiles)
        self.counter = GramCounter()
        self.place, self.generation = np.zeros((len(self.languages), 0), np.int64), self.counter.generation
        self.ranks = [{g: i for i, g in enumerate(profiles[lang])} for lang in self.languages]

    def _places(self, numbers: np.ndarray) -> np.ndarray:
        """Ranks of the numbered n-grams in each profile, -1 where it lacks them."""
        if self.generation != self.counter.generation:
            self.place, self.generation = np.zeros((len(self.languages), 0), np.int64), self.counter.generation
        if new := self.counter.grams[self.place.shape[1] :]:
            self.place = np.concatenate([self.place, np.array([[r.get(g, -1) for g in new] for r in self.ranks], np.int64)], axis=1)
        return self.place[:, numbers]

    def identify(self, text: str | None) -> tuple[str, float]:
        if text is None or not self.languages:
            return UNKNOWN, 0.0
        numbers, _ = self.counter.ranked(text, self.top)
        if not len(numbers):
            return UNKNOWN, 0.0
        places = self._places(numbers)
        away = np.where(places < 0, self.top, np.minimum(np.abs(places - np.arange(len(numbers))), self.top)).sum(axis=1)
        best = int(np.argmin(away))
        others = np.delete(away, best)
        second = int(others.min()) if len(others) else self.top * len(numbers)
        total = int(away[best]) + second
        return self.languages[best], second / total if total else 0.5


def predicted(text: Column, profiles: dict[str, list[str]], top: int = TOP) -> Column:
    """struct(lang_pred, score) of a text column."""

    @F.pandas_udf("lang_pred string, score double")
    def of(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        known = Identifier(profiles, top)
        for texts in batches:
            yield pd.DataFrame([known.identify(t) for t in texts], columns=["lang_pred", "score"])

    return of(text)
