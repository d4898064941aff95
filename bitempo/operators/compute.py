"""Arithmetic on earlier results, so that no model does it."""

from __future__ import annotations

import operator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.canon import canon_float
from ..functions.timeaxis import ALLEN, allen

FUNCTIONS = ("count", "sum", "min", "max", "topk", "filter", "relation")
_TESTS = {"=": operator.eq, "!=": operator.ne, "<": operator.lt, "<=": operator.le, ">": operator.gt, ">=": operator.ge}


def compute(df: DataFrame, fn: str, field: str | None = None, k: int | None = None, test: tuple[str, object] | None = None, ties: tuple[str, ...] = (), ends: tuple[str, str, str, str] | None = None, relation: str | None = None) -> DataFrame:
    """One value (column ``value``) for count, sum, min and max; rows for topk, filter and relation.

    Sums are of decimals, so they do not depend on the order of their terms. ``ties`` complete the order of a top-k.
    """
    if fn == "count":
        return df.agg(F.count(F.lit(1)).alias("value"))
    if fn == "sum":
        return df.agg(F.coalesce(F.sum(canon_float(F.col(field).cast("double")).cast("decimal(38,9)")), F.lit(0)).cast("double").alias("value"))
    if fn in ("min", "max"):
        return df.agg({"min": F.min, "max": F.max}[fn](field).alias("value"))
    if fn == "topk":
        return df.orderBy(F.desc(field), *ties).limit(k)
    if fn == "filter":
        name, value = test
        return df.where(_TESTS[name](F.col(field), value))
    if fn == "relation":
        if relation not in ALLEN:
            raise ValueError(f"no such relation: {relation}")
        return df.where(allen(*ends) == relation)
    raise ValueError(f"fn must be one of {FUNCTIONS}")
