"""Notes: facts of weekly windows, their admission, and their quarantine. Notes hint; they are never evidence."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.timeaxis import ALLEN, WEEK, week_floor
from ..operators.bandjoin import interval_join


def weekly_facts(edges: DataFrame) -> DataFrame:
    """(window_s, window_e, edges, nodes, top_node, top_edges) of each week."""
    week = week_floor("t").alias("window_s")
    counted = edges.groupBy(week, F.col("src").alias("node")).agg(F.count(F.lit(1)).alias("n"))
    lead = counted.groupBy("window_s").agg(F.sum("n").alias("edges"), F.max(F.struct("n", (-F.col("node")).alias("neg"))).alias("top"))
    nodes = edges.select(week, F.explode(F.array("src", "dst")).alias("node")).distinct().groupBy("window_s").agg(F.count(F.lit(1)).alias("nodes"))
    return lead.join(nodes, "window_s").select("window_s", (F.col("window_s") + 7 * 86_400_000_000).alias("window_e"), "edges", "nodes", (-F.col("top.neg")).alias("top_node"), F.col("top.n").alias("top_edges"))


def write_notes(facts: DataFrame, created_tt: int) -> DataFrame:
    """(note_id, window_s, window_e, created_tt, facts, text, quarantined) by the scripted summarizer."""
    text = F.concat(F.lit("In this week "), F.col("nodes"), F.lit(" nodes exchanged "), F.col("edges"), F.lit(" events; node "), F.col("top_node"), F.lit(" sent "), F.col("top_edges"), F.lit("."))
    held = F.map_from_arrays(F.array(*[F.lit(c) for c in ("edges", "nodes", "top_node", "top_edges")]), F.array(*[F.col(c).cast("double") for c in ("edges", "nodes", "top_node", "top_edges")]))
    return facts.select(F.sha2(F.concat_ws("|", "window_s", F.lit(created_tt)), 256).alias("note_id"), "window_s", "window_e", F.lit(created_tt).cast("long").alias("created_tt"), held.alias("facts"), text.alias("text"), F.lit(False).alias("quarantined"))


def admitted(notes: DataFrame) -> DataFrame:
    """Notes whose every stated number is one of their computed facts."""
    stated = F.transform(F.regexp_extract_all("text", F.lit(r"-?\d+(?:\.\d+)?"), 0), lambda x: x.cast("double"))
    return notes.where(F.forall(stated, lambda x: F.array_contains(F.map_values("facts"), x)))


def quarantine(notes: DataFrame, corrections: DataFrame) -> DataFrame:
    """Notes with ``quarantined`` set if a correction after their making overlaps their window.

    Corrections are put into the weeks they touch and reduced to the last transaction time of each week and kind of cut first, so the
    join is an equi-join on weeks with one row of each week on one side.
    """
    week = WEEK
    # weeks outside those of the notes are not made, so an open correction takes no more of them
    lo, hi = notes.agg(F.min("window_s"), F.max("window_s")).first()
    begin, last = F.greatest("vt_s", F.lit(lo).cast("long")), F.least(F.col("vt_e") - 1, F.lit(hi).cast("long"))
    bounded = corrections.where("op = 'correct' and vt_s < vt_e").where(begin <= last)
    weeks = F.sequence(week_floor(begin), week_floor(last), F.lit(week).cast("long"))
    touched = bounded.select(F.explode(weeks).alias("window_s"), "tt").groupBy("window_s").agg(F.max("tt").alias("last_tt"))
    return notes.join(touched, "window_s", "left").withColumn("quarantined", F.col("quarantined") | F.coalesce(F.col("last_tt") > F.col("created_tt"), F.lit(False))).drop("last_tt").select(*notes.columns)


def quarantine_any(notes: DataFrame, corrections: DataFrame) -> DataFrame:
    """The same for windows of any length: an interval join in slices of a week."""
    windows = notes.select("note_id", "created_tt", F.col("window_s").alias("a_s"), F.col("window_e").alias("a_e"))
    hit = corrections.where("op = 'correct' and vt_s < vt_e").select(F.col("vt_s").alias("b_s"), F.col("vt_e").alias("b_e"), F.col("tt").alias("c_tt"))
    sharing = tuple(r for r in ALLEN if r not in ("before", "after", "meets", "met_by"))
    late = interval_join(windows, hit, [], sharing, WEEK).where("c_tt > created_tt").select("note_id").distinct()
    return notes.drop("quarantined").join(late.withColumn("quarantined", F.lit(True)), "note_id", "left").withColumn("quarantined", F.coalesce("quarantined", F.lit(False)))


def citable(notes: DataFrame, by_tt: int | None = None) -> DataFrame:
    """Context for planners and reporters: notes that are not withdrawn, made by ``by_tt``."""
    kept = notes.where("not quarantined")
    return kept if by_tt is None else kept.where(F.col("created_tt") <= by_tt)


def stated_numbers(text: str) -> list[float]:
    return [float(x) for x in re.findall(r"-?\d+(?:\.\d+)?", text)]
