"""Canonical values and digests: equal results have equal bytes, on any partitioning."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Columns that tell of the present belief, not of the pinned one; they stay out of result digests.
BELIEF_COLUMNS = frozenset({"tt_s", "tt_e", "version_id", "source", "provenance_ref"})
DIGITS = 9


def canon_float(c: Column | str, digits: int = DIGITS) -> Column:
    """Rounded; NaN becomes null and -0.0 becomes 0.0."""
    c = F.col(c) if isinstance(c, str) else c
    rounded = F.round(F.when(F.isnan(c), None).otherwise(c), digits)
    return F.when(rounded == 0, F.lit(0.0)).otherwise(rounded)


def canonical_row(df: DataFrame, leave_out: frozenset[str] = frozenset()) -> Column:
    """JSON of a row with its fields in order of name and its doubles canonical; nulls are kept."""
    fields = sorted(f.name for f in df.schema if f.name not in leave_out)
    kinds = {f.name: f.dataType.simpleString() for f in df.schema}

    def value(name: str) -> Column:
        c = F.col(f"`{name}`")
        if kinds[name] in ("double", "float"):
            c = F.format_number(canon_float(c.cast("double")), DIGITS)
        elif kinds[name].startswith("map"):
            c = F.array_sort(F.map_entries(c))
        return c.alias(name)

    return F.to_json(F.struct(*[value(n) for n in fields]), {"ignoreNullFields": "false"})


def result_digest(df: DataFrame, leave_out: frozenset[str] = BELIEF_COLUMNS) -> str:
    """SHA-256 over the canonical rows in order. For pages, which are small; see :func:`store_digest` for tables."""
    lines = sorted(r[0] for r in df.select(canonical_row(df, leave_out).alias("line")).collect())
    return hashlib.sha256("\n".join(lines).encode()).hexdigest()


def store_digest(df: DataFrame, leave_out: frozenset[str] = frozenset()) -> str:
    """SHA-256 of a table whatever the order of its rows; equal rows count each time.

    The hashes of all rows are added word by word, and their number and sums are hashed: every task sends one row, and none is dealt out. That
    tells tables apart that differ by chance or mistake; it does not withstand one who makes up rows to fit given sums.
    """
    rows = df.select(F.sha2(canonical_row(df, leave_out), 256).alias("h"))
    words = [F.conv(F.substring("h", 1 + 8 * i, 8), 16, 10).cast("long") for i in range(8)]
    # halves of words, so that sums of longs hold for 2^47 rows
    halves = [F.sum(x) for w in words for x in (F.shiftright(w, 16), w.bitwiseAND(F.lit(0xFFFF)))]
    totals = rows.agg(F.count(F.lit(1)), *[F.coalesce(x, F.lit(0)) for x in halves]).first()
    return hashlib.sha256("|".join(map(str, totals)).encode()).hexdigest()
