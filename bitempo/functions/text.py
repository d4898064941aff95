"""Text functions: name folding, data fences, token estimates."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

TOKENS_PER_CHARACTER = 0.65
FENCE_OPEN, FENCE_CLOSE = "<<data>>", "<</data>>"


def fold_name(c: Column | str) -> Column:
    """Lower case, single spaces, trimmed."""
    c = F.col(c) if isinstance(c, str) else c
    return F.trim(F.regexp_replace(F.lower(c), r"\s+", " "))


def fence(c: Column | str, most: int = 2000) -> Column:
    """Stored text as quoted data for a prompt: cut to ``most`` characters, control characters and fence marks taken out, delimited."""
    c = F.col(c) if isinstance(c, str) else c
    body = F.substring(F.coalesce(c, F.lit("")), 1, most)
    body = F.regexp_replace(body, r"[\x00-\x08\x0B-\x1F\x7F]", " ")
    body = F.replace(F.replace(F.replace(body, F.lit("\\"), F.lit("\\\\")), F.lit("<<"), F.lit("\\<\\<")), F.lit(">>"), F.lit("\\>\\>"))
    return F.concat(F.lit(FENCE_OPEN + "\n"), body, F.lit("\n" + FENCE_CLOSE))


def approx_tokens(c: Column | str, rate: float = TOKENS_PER_CHARACTER) -> Column:
    c = F.col(c) if isinstance(c, str) else c
    return F.ceil(F.char_length(F.coalesce(c, F.lit(""))) * F.lit(rate)).cast("long")


def register_sql(spark: SparkSession) -> None:
    """SQL functions: covers(s, e, t), overlap_share(a, b, c, d), allen_relation(a, b, c, d)."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION covers(s BIGINT, e BIGINT, t BIGINT) RETURNS BOOLEAN RETURN s <= t AND e > t")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION overlap_share(a BIGINT, b BIGINT, c BIGINT, d BIGINT) RETURNS DOUBLE "
        "RETURN greatest(0, least(b, d) - greatest(a, c)) / ((b - a) + (d - c) - greatest(0, least(b, d) - greatest(a, c)))"
    )
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION allen_relation(a BIGINT, b BIGINT, c BIGINT, d BIGINT) RETURNS STRING RETURN CASE "
        "WHEN b < c THEN 'before' WHEN b = c THEN 'meets' WHEN d < a THEN 'after' WHEN d = a THEN 'met_by' WHEN a = c AND b = d THEN 'equals' "
        "WHEN a = c AND b < d THEN 'starts' WHEN a = c THEN 'started_by' WHEN b = d AND a > c THEN 'finishes' WHEN b = d THEN 'finished_by' "
        "WHEN a > c AND b < d THEN 'during' WHEN a < c AND b > d THEN 'contains' WHEN a < c THEN 'overlaps' ELSE 'overlapped_by' END"
    )
