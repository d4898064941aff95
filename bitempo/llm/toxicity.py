"""Toxic spans by a linear-chain conditional random field over words, and document scores from its marginals.

Two states, clean and toxic. A word's emission weighs its features: the word, its first four to six letters, and whether it
is in capitals. Forward-backward gives the probability of each word being toxic; runs of probable words are spans with their
character offsets; a document's score is a logistic function of its evidence, which joins the marginals of all words that have a feature.

Labels are of documents, so the field learns from token labels derived from them: words of toxic training texts are labelled if they show
a feature that toxic texts have in many contexts and clean ones hardly ever.

Most words have no feature of any weight and are not in capitals. Between the words that do or are, the chain's steps are all alike, so
a run of them is applied as a power of one 2 x 2 matrix: the exact marginals at a cost that follows the words that matter. Words in
capitals without a feature bear on their neighbours' marginals and can be in spans, but are no evidence of their own.

Cases: null, empty and word-less texts have no evidence and the least score; repeated rows get equal results; texts of
any length are read whole; with no labelled row, or labels of one kind alone, every text scores 0. The training sample is bounded by
``PER_LABEL`` labelled texts, chosen by a hash of the id; each is read whole, and the field learns from stretches of ``size`` words that cover
all its marked words, and one more at random. Other columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections import Counter, defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: At most about so many labelled texts of each label are learned from.
PER_LABEL = {1: 2000, 0: 4000}
THRESHOLD = 0.7
EPSILON = 1e-3  # evidence below it counts as hardly any
_WORD = re.compile(r"\w+")
_PREFIXES = (4, 5, 6)


def features(word: str) -> list[str]:
    """Features of a lower-cased word."""
    return ["w=" + word, *[f"p{n}={word[:n]}" for n in _PREFIXES if len(word) >= n]]


def telling_features(texts: list[list[str]], toxic: list[int], least: int = 3, purity: float = 0.75, doubt: float = 0.01) -> list[str]:
    """Features that mark toxic texts.

    A feature's evidence is the number of toxic texts that show it, or of its different neighbours there if that is less, so
    that copies of one text or passage count once. Taken are features whose evidence would hardly arise among
    all candidates if toxic texts were any texts.
    """
    count_toxic: Counter[str] = Counter()
    for words, y in zip(texts, toxic):
        if y:
            count_toxic.update({f for w in set(words) for f in features(w)})
    count_toxic = Counter({f: n for f, n in count_toxic.items() if n >= least})
    count_clean: Counter[str] = Counter()
    for words, y in zip(texts, toxic):
        if not y:
            count_clean.update({f for w in set(words) for f in features(w) if f in count_toxic})
    bad = sum(toxic)
    ratio = (len(toxic) - bad) / max(1, bad)
    pure = {f for f, n in count_toxic.items() if n * ratio >= purity * (n * ratio + count_clean[f])}
    near: dict[str, set[tuple[str, str]]] = defaultdict(set)
    for words, y in zip(texts, toxic):
        if not y:
            continue
        for i, w in enumerate(words):
            for f in features(w):
                if f in pure:
                    near[f].add((words[i - 1] if i else "", words[i + 1] if i + 1 < len(words) else ""))
    evidence = {f: min(count_toxic[f], len(near[f])) for f in pure}
    share, needed = min(0.9, bad / len(toxic)), math.log(max(1, len(count_toxic)) / doubt)

    def surprise(f: str) -> float:
        """How unlikely the feature's evidence is among texts of the common share of toxic ones (n times the divergence)."""
        n1, n0 = evidence[f], count_clean[f]
        q = n1 / (n1 + n0)
        return n1 * math.log(q / share) + (n0 * math.log((1 - q) / (1 - share)) if n0 else 0.0) if q > share else 0.0

    return sorted(f for f, n in evidence.items() if n >= least and surprise(f) >= needed)


@dataclass
class Model:
    """Weights of a fitted field: ``weights`` of features, ``bias`` of any word, log transition scores and the start."""

    weights: dict[str, float] = field(default_factory=dict)
    bias: float = -20.0
    moves: tuple[tuple[float, float], tuple[float, float]] = ((0.0, 0.0), (0.0, 0.0))
    start: float = 0.0
    capitals: float = 0.0
    scale: tuple[float, float] = (1.0, 0.0)  # slope and offset from the log of a document's evidence to its log odds

    def emission(self, word: str) -> float:
        """Log weight of the toxic over the clean state for a lower-cased word."""
        return self.bias + sum(self.weights.get(f, 0.0) for f in features(word))


def _windows(texts: list[list[str]], toxic: list[int], marks: set[str], size: int, rng) -> list[tuple[list[str], list[int]]]:
    """Stretches of words with token labels: as few as cover all marked words, each begun at random before one, and one at random from each text."""
    out = []
    for words, y in zip(texts, toxic):
        if not words:
            continue
        marked = [i for i, w in enumerate(words) if any(f in marks for f in features(w.lower()))]
        label = set(marked) if y else set()
        starts, covered = {rng.randrange(max(1, len(words) - size + 1))}, -1
        for i in marked:
            if i >= covered:
                start = max(0, i - rng.randrange(size))
                covered = start + size
                starts.add(start)
        for s in sorted(starts):
            part = words[s : s + size]
            out.append((part, [int(s + k in label) for k in range(len(part))]))
    return out


def fit(rows: list[tuple[str, int]], rounds: int = 100, size: int = 24, seed: int = 7) -> Model:
    """Fit a field to (text, label) rows by gradient ascent on the conditional likelihood of the derived token labels."""
    import random

    rows = sorted(set(rows))
    toxic = [y for _, y in rows]
    if not 0 < sum(toxic) < len(toxic):
        return Model()
    one: dict[str, str] = {}  # equal words are held once
    raw = [[one.setdefault(w, w) for w in _WORD.findall(t)] for t, _ in rows]
    kept_texts = [t for t, _ in rows]
    small = {w: one.setdefault(w.lower(), w.lower()) for w in list(one)}
    lowered = [[small[w] for w in words] for words in raw]
    marks = set(telling_features(lowered, toxic))
    windows = _windows(raw, toxic, marks, size, random.Random(seed))
    # features seen on labelled tokens, and those words' other features; the rest share the bias
    kept = sorted({f for words, ys in windows for w, y in zip(words, ys) if y for f in features(w.lower())})
    number = {f: i for i, f in enumerate(kept)}
    n, width = len(windows), 1 + len(_PREFIXES)
    ids = np.full((n, size, width), len(kept))
    upper, gold, live = np.zeros((n, size)), np.zeros((n, size), int), np.zeros((n, size), bool)
    for i, (words, ys) in enumerate(windows):
        for k, (w, y) in enumerate(zip(words, ys)):
            live[i, k], gold[i, k], upper[i, k] = True, y, len(w) > 1 and w.isupper()
            for j, f in enumerate(features(w.lower())):
                ids[i, k, j] = number.get(f, len(kept))
    theta = np.zeros(len(kept) + 1 + 1 + 1 + 4)  # features, (none), bias, capitals, moves
    theta[len(kept) + 1] = -3.0
    # the observed counts
    seen = np.zeros_like(theta)
    y1 = (gold == 1) & live
    np.add.at(seen, ids[y1].ravel(), 1)
    seen[-6], seen[-5] = y1.sum(), upper[y1].sum()
    pairs = live[:, 1:] & live[:, :-1]
    np.add.at(seen, len(theta) - 4 + 2 * gold[:, :-1][pairs] + gold[:, 1:][pairs], 1)
    first, second = np.zeros_like(theta), np.zeros_like(theta)
    flat = ids.reshape(-1, width)
    for step in range(1, rounds + 1):
        theta[len(kept)] = 0.0
        emit = theta[ids].sum(axis=2) + theta[-6] + theta[-5] * upper
        marginal, joint = _forward_backward(emit, live, theta[-4:].reshape(2, 2))
        wanted = np.bincount(flat.ravel(), np.repeat(marginal.ravel(), width), len(kept) + 1)
        model = np.concatenate([wanted, [marginal.sum(), (marginal * upper).sum()], joint])
        slope = (seen - model) / n - 2e-4 * theta
        slope[len(kept)] = 0.0
        first, second = 0.9 * first + 0.1 * slope, 0.99 * second + 0.01 * slope**2
        theta += 0.3 * (first / (1 - 0.9**step)) / (np.sqrt(second / (1 - 0.99**step)) + 1e-6)
    weights = {f: float(theta[i]) for f, i in number.items() if abs(theta[i]) > 1e-3}
    m = theta[-4:].reshape(2, 2)
    model = Model(weights, float(theta[-6]), ((float(m[0, 0]), float(m[0, 1])), (float(m[1, 0]), float(m[1, 1]))), 0.0, float(theta[-5]))
    tagger = Tagger(model)
    model.scale = _calibrated([tagger.evidence(t)[0] for t in kept_texts], toxic)
    return model


def _calibrated(evidence: list[float], toxic: list[int], rounds: int = 60) -> tuple[float, float]:
    """Slope and offset of a logistic curve over the log of the evidence, by Newton's method with a mild prior."""
    x = np.stack([np.log(np.array(evidence) + EPSILON), np.ones(len(evidence))], axis=1)
    y, w, prior = np.array(toxic, float), np.array([1.0, 0.0]), np.diag([0.5, 0.05])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + prior, x.T @ (y - p) - prior @ w)
        w = w + np.clip(step, -1, 1)
    return float(max(w[0], 0.05)), float(w[1])


def _forward_backward(emit: np.ndarray, live: np.ndarray, moves: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Toxic marginals of each place and the summed expectation of the four moves, over rows of equal width."""
    n, size = emit.shape
    step = np.exp(moves)
    local = np.stack([np.ones_like(emit), np.exp(np.clip(emit, -40, 40))], axis=2)
    ahead, back = np.zeros((n, size, 2)), np.ones((n, size, 2))
    ahead[:, 0] = local[:, 0]
    ahead[:, 0] /= ahead[:, 0].sum(axis=1, keepdims=True)
    for t in range(1, size):
        now = (ahead[:, t - 1] @ step) * local[:, t]
        ahead[:, t] = np.where(live[:, t, None], now / now.sum(axis=1, keepdims=True), ahead[:, t - 1])
    joint = np.zeros(4)
    for t in range(size - 2, -1, -1):
        then = (local[:, t + 1] * back[:, t + 1]) @ step.T
        back[:, t] = np.where(live[:, t + 1, None], then / then.sum(axis=1, keepdims=True), 1.0)
        both = ahead[:, t, :, None] * step[None] * (local[:, t + 1] * back[:, t + 1])[:, None, :]
        both /= both.sum(axis=(1, 2), keepdims=True)
        joint += (both * live[:, t + 1, None, None]).sum(axis=0).ravel()
    p = ahead * back
    return np.where(live, p[:, :, 1] / p.sum(axis=2), 0.0), joint


class Tagger:
    """Exact marginals of whole texts under a fitted model."""

    def __init__(self, model: Model, remember: int = 200_000):
        self.model, self.remember = model, remember
        self.known: dict[str, bool] = {}
        (a, b), (c, d) = model.moves
        self.step = np.exp(np.array([[a, b], [c, d]]))
        self.plain = np.array([1.0, math.exp(max(model.bias, -40.0))])
        self.one = self.step * self.plain  # a move into a word without features
        self.powers = [self._scaled(self.one)]
        while len(self.powers) < 40:
            self.powers.append(self._scaled(self.powers[-1] @ self.powers[-1]))

    @staticmethod
    def _scaled(m: np.ndarray) -> np.ndarray:
        return m / m.sum()

    def _run(self, row: np.ndarray, n: int) -> np.ndarray:
        """Row vector after ``n`` moves into words without features."""
        k = 0
        while n:
            if n & 1:
                row = row @ self.powers[k]
                row = row / row.sum()
            n >>= 1
            k += 1
        return row

    def _run_back(self, column: np.ndarray, n: int) -> np.ndarray:
        k = 0
        while n:
            if n & 1:
                column = self.powers[k] @ column
                column = column / column.sum()
            n >>= 1
            k += 1
        return column

    def _matters(self, words: set[str]) -> set[str]:
        known = self.known
        if len(known) > self.remember:
            known.clear()
        out = set()
        weights = self.model.weights
        for w in words:
            hit = known.get(w)
            if hit is None:
                hit = known[w] = any(f in weights for f in features(w))
            if hit:
                out.add(w)
        return out

    def tag(self, text: str | None, spans: bool = True) -> tuple[float, list[tuple[int, int, float]]]:
        """Score of the document, and its spans (start, end, probability) in characters."""
        if not self.model.weights:
            return 0.0, []
        evidence, found = self.evidence(text)
        slope, offset = self.model.scale
        return 1 / (1 + math.exp(-max(-40.0, min(40.0, slope * math.log(evidence + EPSILON) + offset)))), found if spans else []

    def evidence(self, text: str | None) -> tuple[float, list[tuple[int, int, float]]]:
        """Evidence that some word is toxic, -log of the chance that none is by the marginals of the words with a feature; and the spans."""
        if not text or not self.model.weights:
            return 0.0, []
        lowered = text.lower()
        words = _WORD.findall(lowered)
        hot = self._matters(set(words))
        if not hot:
            return 0.0, []
        raw = list(_WORD.finditer(text))
        if len(raw) != len(words):  # lower-casing changed the length of a word's marks
            words = [m.group().lower() for m in raw]
            hot = self._matters(set(words))
        upper = [self.model.capitals != 0 and len(m.group()) > 1 and m.group().isupper() for m in raw]
        at = [i for i, w in enumerate(words) if upper[i] or w in hot]
        local = []
        for i in at:
            score = self.model.emission(words[i]) + self.model.capitals * upper[i]
            local.append(np.array([1.0, math.exp(min(40.0, max(-40.0, score)))]))
        ahead, row, last = [], None, -1
        for i, here in zip(at, local):
            if row is None:
                row = here.copy() if i == 0 else (self._run(self._scaled(self.plain), i - 1) @ self.step) * here
            else:
                row = (self._run(row, i - last - 1) @ self.step) * here
            row = row / row.sum()
            ahead.append(row)
            last = i
        column = self._run_back(np.array([0.5, 0.5]), len(words) - 1 - last)
        marginals = [0.0] * len(at)
        for k in range(len(at) - 1, -1, -1):
            p = ahead[k] * column
            marginals[k] = float(p[1] / p.sum())
            if k:
                column = self.step @ (local[k] * column)
                column = self._run_back(column / column.sum(), at[k] - at[k - 1] - 1)
        found: list[list] = []
        total, end = 0.0, None
        for i, p in zip(at, marginals):
            if words[i] in hot:
                total -= math.log(max(1 - p, 1e-12))
            if p >= 0.5:
                m = raw[i]
                if found and end == i - 1:
                    found[-1][1], found[-1][2] = m.end(), max(found[-1][2], p)
                else:
                    found.append([m.start(), m.end(), p])
                end = i
        return total, [tuple(s) for s in found]


def training_sample(docs: DataFrame, labels: DataFrame, per_label: dict[int, int] = PER_LABEL) -> list[tuple[str, int]]:
    """At most about ``per_label[y]`` labelled texts of each label y; ``docs(doc_id, text)`` and ``labels(doc_id, toxic)``."""
    labels = labels.where(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull()).select("doc_id", "toxic")
    sizes = {r["toxic"]: r["n"] for r in labels.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    share = lambda y: min(1.0, per_label[y] / sizes.get(y, 1)) * 1_000_000
    chosen = labels.where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < F.when(F.col("toxic") == 1, share(1)).otherwise(share(0)))
    # the chosen ids are bounded by the parameter, so they may be broadcast
    rows = docs.where(F.col("text").isNotNull()).select("doc_id", "text").join(F.broadcast(chosen), "doc_id").select("text", "toxic")
    return [(r["text"], int(r["toxic"])) for r in rows.toLocalIterator()]


def train(docs: DataFrame, labels: DataFrame, per_label: dict[int, int] = PER_LABEL) -> Model:
    return fit(training_sample(docs, labels, per_label))


def tagged(text: Column, model: Model) -> Column:
    """struct(score, spans) of a text column."""

    @F.pandas_udf("score double, spans array<struct<start:int,end:int,p:double>>")
    def of(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        tagger = Tagger(model)
        for texts in batches:
            found = [tagger.tag(t) for t in texts]
            yield pd.DataFrame({"score": [s for s, _ in found], "spans": [[{"start": a, "end": b, "p": p} for a, b, p in spans] for _, spans in found]})

    return of(text)
