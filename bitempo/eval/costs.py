"""Cost measures: size of a store, prompt tokens, and how near the guard's estimates come."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import approx_tokens
from ..plans.guard import estimate
from ..plans.registry import REGISTRY
from ..plans.store import Store


def store_bytes(spark: SparkSession, folder: str) -> int:
    """Bytes of a stored table's files, by Spark's own listing, so any file system that it reads will do."""
    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(folder)
    return files.agg(F.coalesce(F.sum("length"), F.lit(0))).first()[0]


def tokens_per_task(prompts: DataFrame, column: str = "prompt") -> DataFrame:
    return prompts.agg(F.count(F.lit(1)).alias("tasks"), F.round(F.avg(approx_tokens(column)), 3).alias("tokens"))


def guard_calibration(store: Store, cases: list[tuple[str, dict]]) -> list[tuple[str, int, int]]:
    """(operator, estimated rows, rows made) of calls."""
    return [(op, estimate(op, args, store.stats), REGISTRY[op].run(store, args).count()) for op, args in cases]
