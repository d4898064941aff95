"""Slabs of a key's time: an identity with any share of all rows is dealt over many equi-join keys.

A key with n intervals has its time cut into n / ``PER_SLAB`` slabs of equal width, so a key with few rows has one slab and nothing is
repeated for it. Width and origin are exact aggregates, so every evaluation finds the same slabs. An interval is repeated in the slabs that it
overlaps; intervals that overlap one another meet in the slab of the later start.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.timeaxis import OPEN_END

#: Intervals that a slab holds the starts of, on average.
PER_SLAB = 64


def slab_layout(df: DataFrame, key: str, s: str, e: str, per: int | None = None) -> DataFrame:
    """(key, slab_lo, slab_width, slab_count): one row for each key, combined map-side."""
    last = F.when(F.col(e) < OPEN_END, F.greatest(s, e)).otherwise(F.col(s))
    spans = df.groupBy(key).agg(F.count(F.lit(1)).alias("n"), F.min(s).alias("slab_lo"), F.max(last).alias("hi"))
    wanted = F.floor((F.col("n") + F.lit((per or PER_SLAB) - 1)) / F.lit(per or PER_SLAB)).cast("long")
    width = F.expr("greatest(1L, (hi - slab_lo) div wanted + 1)")
    return spans.withColumn("wanted", wanted).withColumn("slab_width", width).select(key, "slab_lo", "slab_width", F.expr("(hi - slab_lo) div slab_width + 1").alias("slab_count"))


def slab_of(t: str) -> Column:
    """Number of the slab that holds time ``t``, of rows that have their key's layout; times out of the layout fall into its ends."""
    return F.expr(f"greatest(0L, least(slab_count - 1, ({t} - slab_lo) div slab_width))")


def over_slabs(df: DataFrame, layout: DataFrame, key: str, s: str, e: str) -> DataFrame:
    """Rows repeated in each slab that their [s, e) overlaps, with ``slab`` and their key's layout."""
    return df.join(layout, key).withColumn("slab", F.explode(F.sequence(slab_of(s), slab_of(f"greatest({s}, {e} - 1)"))))
