"""Transaction times: strictly increasing, never behind the physical clock."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def log_shard(ident: Column | str, shards: int = 16) -> Column:
    """Shard of the log that an identity's batches go to; every shard has a clock of its own."""
    ident = F.col(ident) if isinstance(ident, str) else ident
    return F.pmod(F.crc32(ident.cast("string").cast("binary")), F.lit(shards)).cast("int")


#: Batch ids of one range of a shard; a range is stamped by one task.
RANGE = 1 << 20


def stamp_transaction_time(log: DataFrame, shard: str = "log_shard", order: str = "batch_id", phys: str = "phys", high_water: int | None = None) -> DataFrame:
    """Add ``tt`` = max(phys, previous tt + 1) for each batch, in closed form: place + running max of (phys - place).

    ``high_water`` is the last time given out before (by another batch of the log), which all new times exceed. Places and maxima are found
    within ranges of ``RANGE`` batch ids of a shard; what lies before a range comes from one row for each range.
    """
    window = Window.partitionBy(shard, "_range").orderBy(order)
    local = log.withColumn("_range", F.floor(F.col(order) / F.lit(RANGE)).cast("long")).withColumn("_place", F.dense_rank().over(window).cast("long"))
    local = local.withColumn("_ahead", F.col(phys) - F.col("_place"))
    before = Window.partitionBy(shard).orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    ranges = local.groupBy(shard, "_range").agg(F.max("_place").alias("_places"), F.max("_ahead").alias("_most"))
    ranges = ranges.withColumn("_base", F.coalesce(F.sum("_places").over(before), F.lit(0))).withColumn("_prior", F.max(F.col("_most") - F.col("_base")).over(before))
    ahead = local.join(ranges.select(shard, "_range", "_base", "_prior"), [shard, "_range"])
    ahead = ahead.withColumn("_most", F.max("_ahead").over(window.rangeBetween(Window.unboundedPreceding, Window.currentRow)) - F.col("_base")).withColumn("_place", F.col("_place") + F.col("_base"))
    tt = F.col("_place") + F.greatest("_most", "_prior")
    if high_water is not None:
        tt = F.greatest(tt, F.lit(high_water) + F.col("_place"))
    return ahead.withColumn("tt", tt).select(*log.columns, "tt")
