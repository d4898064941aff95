"""Measures: typed-answer accuracy, support, coverage, validity, bootstrap intervals, as functions and as DataFrame expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.timeaxis import interval_iou
from ..lineage import cut
from ..plans.paging import canonical_json

IOU = 0.5
TOLERANCE = 1e-9
#: Draws of a bootstrap that one task makes.
DRAWS_PER_TASK = 10_000_000


def correct(kind: str, answer, gold, strict_entities: bool = False) -> bool:
    """One answer against gold. Entity sets compare identifiers at any depth unless ``strict_entities``."""
    from ..claims.verifier import identifiers

    if answer is None:
        return False
    if kind in ("count", "value"):
        return isinstance(answer, (int, float)) and not isinstance(answer, bool) and abs(round(answer, 9) - round(gold, 9)) <= TOLERANCE
    if kind == "entity_set":
        if strict_entities:
            return isinstance(answer, list) and sorted(map(str, answer)) == sorted(map(str, gold))
        return identifiers(answer) == identifiers(gold)
    if kind == "interval":
        (a, b), (x, y) = answer, gold
        shared, joint = max(0, min(b, y) - max(a, x)), max(b, y) - min(a, x)
        return (a, b) == (x, y) if joint == 0 else shared / joint >= IOU
    return canonical_json(answer) == canonical_json(gold)


def number_correct(answer: Column, gold: Column) -> Column:
    return F.coalesce(F.abs(F.round(answer, 9) - F.round(gold, 9)) <= TOLERANCE, F.lit(False))


def interval_correct(a_s, a_e, g_s, g_e) -> Column:
    return F.coalesce(interval_iou(a_s, a_e, g_s, g_e) >= IOU, F.lit(False))


def set_correct(answer: Column, gold: Column) -> Column:
    return F.coalesce((F.size(F.array_except(answer, gold)) == 0) & (F.size(F.array_except(gold, answer)) == 0), F.lit(False))


def accuracy(scores: DataFrame, by: list[str]) -> DataFrame:
    """(…by, tasks, correct, accuracy) of ``scores(…by, correct)``."""
    return scores.groupBy(*by).agg(F.count(F.lit(1)).alias("tasks"), F.sum(F.col("correct").cast("long")).alias("correct"), F.round(F.avg(F.col("correct").cast("double")), 9).alias("accuracy"))


def accuracy_cube(scores: DataFrame, by: list[str]) -> DataFrame:
    """The same for every combination of the columns, null where a column is summed over."""
    return scores.cube(*by).agg(F.count(F.lit(1)).alias("tasks"), F.round(F.avg(F.col("correct").cast("double")), 9).alias("accuracy"))


def resampled_means(placed: DataFrame, n: int, resamples: int, seed: int) -> DataFrame:
    """(resample, m) of ``placed(place, d)`` with places 0 to n - 1.

    Slot i of a resample holds the task whose place is a hash of (resample, i): exact multinomial resampling without random state. All draws
    are one range, whose size the planner knows, so the tasks' differences travel to the draws and never the draws; means are combined map-side.
    """
    total = resamples * n
    draws = placed.sparkSession.range(0, total, 1, -(-total // DRAWS_PER_TASK))
    resample, slot = F.expr(f"id div {n}L"), F.pmod("id", F.lit(n)).cast("int")
    draws = draws.select(resample.alias("resample"), F.pmod(F.xxhash64(resample, slot, F.lit(seed)), F.lit(n)).cast("int").alias("place"))
    return draws.join(F.broadcast(placed), "place").groupBy("resample").agg(F.avg("d").alias("m"))


def paired_bootstrap(scores: DataFrame, resamples: int = 10_000, seed: int = 1, level: float = 0.95) -> DataFrame:
    """(diff, low, high) of the mean difference of ``scores(task, a, b)``, resampled by task.

    Tasks are numbered in one partition (suites are small), and the numbered differences are kept, so that scores are made once.
    """
    from pyspark.sql import Window

    spark = scores.sparkSession
    placed = cut(scores.select((F.row_number().over(Window.orderBy("task")) - 1).alias("place"), (F.col("a").cast("double") - F.col("b").cast("double")).alias("d")))
    n = placed.count()
    if n == 0:
        return spark.createDataFrame([], "diff double, low double, high double")
    means = resampled_means(placed, n, resamples, seed)
    tail = (1 - level) / 2
    bounds = means.agg(F.percentile("m", F.lit(tail)).alias("low"), F.percentile("m", F.lit(1 - tail)).alias("high"))
    return placed.agg(F.avg("d").alias("diff")).join(bounds, F.lit(True)).select(*[F.round(c, 6).alias(c) for c in ("diff", "low", "high")])


def support_report(rows: list[dict]) -> dict:
    """Rates with their denominators from per-task rows (correct, emitted, measured, unsupported, valid_first, executed)."""
    tasks = len(rows)
    emitted = [r for r in rows if r["emitted"]]
    measured = [r for r in rows if r["measured"]]
    share = lambda n, d: round(n / d, 6) if d else None
    return {
        "tasks": tasks, "accuracy": share(sum(r["correct"] for r in rows), tasks),
        "coverage": share(len(emitted), tasks), "emitted": len(emitted), "conditional_accuracy": share(sum(r["correct"] for r in emitted), len(emitted)),
        "measured": len(measured), "unsupported": sum(r["unsupported"] for r in measured), "unsupported_rate": share(sum(r["unsupported"] for r in measured), len(measured)),
        "first_validity": share(sum(r["valid_first"] for r in rows), tasks), "execution_success": share(sum(r["executed"] for r in rows), tasks),
    }
