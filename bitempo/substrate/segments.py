"""Belief as sets, without a sequential fold: at a point of valid time the operation of greatest transaction time that covers it decides."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.timeaxis import OPEN_END, covers
from ..operators.slabs import over_slabs, slab_layout, slab_of


def effective(ops: DataFrame) -> DataFrame:
    """Committed operations with the valid time they decide: a retract decides everything from its start on."""
    ops = ops.where("outcome = 'committed'") if "outcome" in ops.columns else ops
    return ops.withColumn("vt_e", F.when(F.col("op") == "retract", F.lit(OPEN_END)).otherwise(F.col("vt_e"))).where("vt_s < vt_e")


def belief_at(ops: DataFrame, vt: int, tt: int | None = None) -> DataFrame:
    """(ident, w, tt) believed at valid time ``vt`` by transaction time ``tt`` (the present if None); one scan, combined map-side."""
    held = effective(ops).where(covers("vt_s", "vt_e", F.lit(vt)))
    held = held if tt is None else held.where(F.col("tt") <= tt)
    last = held.groupBy("ident").agg(F.max_by(F.struct("op", "w", "tt"), F.struct("tt", "batch_id", "seq")).alias("last"))
    return last.where("last.op != 'retract'").select("ident", "last.w", "last.tt")


def segment_versions(ops: DataFrame) -> DataFrame:
    """(ident, vt_s, vt_e, tt_s, tt_e, w): versions with neighbours of equal belief merged; every snapshot equals the fold's.

    An identity's valid time is cut at all ends of its operations; in each stretch the covering operations follow one another. Stretches meet
    operations in slabs of the identity's time, whose starts are cuts too, so a long history is work for many tasks and no stretch is compared
    with operations of other slabs. Merging takes the cuts between slabs away again.
    """
    held = effective(ops).select("ident", "op", "vt_s", "vt_e", "tt", "batch_id", "w")
    layout = slab_layout(held, "ident", "vt_s", "vt_e")
    slab_end = F.expr("if(slab < slab_count - 1, slab_lo + (slab + 1) * slab_width, null)").alias("slab_end")
    ends = held.select("ident", F.explode(F.array("vt_s", "vt_e")).alias("at")).join(layout, "ident").withColumn("slab", slab_of("at"))
    starts = layout.withColumn("slab", F.explode(F.sequence(F.lit(0).cast("long"), F.col("slab_count") - 1))).withColumn("at", F.expr("slab_lo + slab * slab_width"))
    cuts = ends.select("ident", "slab", "at", slab_end).unionByName(starts.select("ident", "slab", "at", slab_end)).distinct()
    following = F.lead("at").over(Window.partitionBy("ident", "slab").orderBy("at"))
    stretch = cuts.select("ident", "slab", "at", F.coalesce(following, "slab_end").alias("end")).where("end is not null")
    inside = stretch.join(over_slabs(held, layout, "ident", "vt_s", "vt_e"), ["ident", "slab"]).where("vt_s <= at and vt_e >= end")
    after = Window.partitionBy("ident", "at").orderBy("tt", "batch_id")
    chained = inside.withColumn("tt_e", F.coalesce(F.lead("tt").over(after), F.lit(OPEN_END))).where("op != 'retract' and tt < tt_e")
    # merge neighbouring stretches that one operation decided for the same time
    same = Window.partitionBy("ident", "batch_id", "tt", "tt_e").orderBy("at")
    begun = chained.withColumn("new", (F.coalesce(F.lag("end").over(same), F.lit(-OPEN_END)) != F.col("at")).cast("int"))
    numbered = begun.withColumn("run", F.sum("new").over(same))
    merged = numbered.groupBy("ident", "batch_id", "tt", "tt_e", "run").agg(F.min("at").alias("vt_s"), F.max("end").alias("vt_e"), F.first("w").alias("w"))
    return merged.select("ident", "vt_s", "vt_e", F.col("tt").alias("tt_s"), "tt_e", "w")
