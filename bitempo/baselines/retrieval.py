"""Chunk retrieval over events written out as sentences: term weights, cosine scores, a token window."""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import TOKENS_PER_CHARACTER

WINDOW = 32_768


def serialise_events(edges: DataFrame) -> DataFrame:
    """(eid, t, sentence). Time is text here; when something was believed is not told at all."""
    # a calendar reading without a zone, so that sentences do not depend on the session
    at = F.date_format(F.expr("timestampadd(MICROSECOND, t, TIMESTAMP_NTZ'1970-01-01 00:00:00')"), "yyyy-MM-dd HH:mm:ss")
    return edges.select("eid", "t", F.concat_ws(" ", F.lit("user"), "src", "etype", F.lit("user"), "dst", F.lit("on"), at, F.lit("weight"), F.format_number("w", 2)).alias("sentence"))


def chunks(edges: DataFrame, n: int) -> DataFrame:
    """(chunk, events, text): ``n`` neighbouring event ids a chunk, in order of id."""
    said = serialise_events(edges).withColumn("chunk", F.floor(F.col("eid") / F.lit(n)).cast("long"))
    rows = said.groupBy("chunk").agg(F.sort_array(F.collect_list(F.struct("eid", "sentence"))).alias("held"))
    return rows.select("chunk", F.size("held").cast("long").alias("events"), F.concat_ws(". ", F.col("held.sentence")).alias("text"))


def terms(text: str) -> list[str]:
    return re.findall(r"[a-z0-9]+", text.lower())


def term_weights(held: DataFrame) -> DataFrame:
    """(chunk, term, weight): term counts times smoothed inverse chunk frequency, scaled to length 1."""
    counts = held.select("chunk", F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z0-9]+"), 0)).alias("term")).groupBy("chunk", "term").agg(F.count(F.lit(1)).alias("n"))
    spread = counts.groupBy("term").agg(F.count(F.lit(1)).alias("df"))
    total = held.agg(F.count(F.lit(1)).alias("all"))
    weighed = counts.join(spread, "term").join(F.broadcast(total), F.lit(True)).withColumn("x", F.col("n") * F.log((F.col("all") + 1) / (F.col("df") + 1)))
    norms = weighed.groupBy("chunk").agg(F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("norm"))
    return weighed.join(norms, "chunk").select("chunk", "term", F.when(F.col("norm") > 0, F.col("x") / F.col("norm")).otherwise(0.0).alias("weight"))


def retrieve_chunks(weights: DataFrame, query: str, k: int) -> DataFrame:
    """(chunk, score) of the ``k`` chunks nearest to the query; ties go to the lower chunk."""
    wanted = weights.where(F.col("term").isin(*sorted(set(terms(query)))))
    scored = wanted.groupBy("chunk").agg(F.round(F.sum("weight"), 9).alias("score"))
    return scored.orderBy(F.desc("score"), "chunk").limit(k)


def retrieve_for_all(weights: DataFrame, prompts: DataFrame, k: int) -> DataFrame:
    """(task, chunk, score, place) of the ``k`` chunks nearest to each of ``prompts(task, prompt)``; all prompts in one pass over the weights."""
    asked = prompts.select("task", F.explode(F.array_distinct(F.regexp_extract_all(F.lower("prompt"), F.lit("[a-z0-9]+"), 0))).alias("term"))
    scored = weights.join(asked, "term").groupBy("task", "chunk").agg(F.round(F.sum("weight"), 9).alias("score"))
    return scored.withColumn("place", F.row_number().over(Window.partitionBy("task").orderBy(F.desc("score"), "chunk"))).where(F.col("place") <= k)


@dataclass(frozen=True)
class Admission:
    k: int
    n: int
    tokens: int
    admitted: bool


def admit(held: DataFrame, k: int, n: int, window: int = WINDOW, rate: float = TOKENS_PER_CHARACTER) -> Admission:
    """Tokens that ``k`` average chunks take, and whether a serving window holds them."""
    mean = held.agg(F.avg(F.char_length("text"))).first()[0] or 0.0
    tokens = int(mean * k * rate)
    return Admission(k, n, tokens, tokens <= window)


def read_events(chunk_rows: list[str]) -> list[tuple[int, str, int, str, float]]:
    """The events that retrieved texts state: an upper bound on what a reader can take from them."""
    found = re.findall(r"user (\d+) (\w+) user (\d+) on ([\d-]+ [\d:]+) weight (-?\d[\d,]*\.\d+)", " ".join(chunk_rows))
    return [(int(a), e, int(b), t, float(w.replace(",", ""))) for a, e, b, t, w in found]


class ChunkRetrieval:
    """Answers from what was retrieved: counts of events are its counts, beliefs are the last value it reads for the user."""

    def __init__(self, edges: DataFrame, k: int = 1, n: int = 256):
        self.held = chunks(edges, n).persist()
        self.weights = term_weights(self.held).persist()
        self.k, self.n = k, n

    def __call__(self, task) -> object:
        top = retrieve_chunks(self.weights, task.prompt, self.k)
        return self.read(task, [r["text"] for r in top.join(self.held, "chunk").select("text").collect()])

    @staticmethod
    def read(task, texts: list[str]) -> object:
        events, p = read_events(texts), task.needs
        mine = [e for e in events if e[0] == p.get("u")]
        if task.template == "a01":
            return mine[-1][4] if mine else None
        if task.template in ("a02",):
            return len(mine) or None
        if task.template == "e01":
            return sorted({str(e[2]) for e in mine}) or None
        return None
