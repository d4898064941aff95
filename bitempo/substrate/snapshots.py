"""Pinned reading of versions, and the invariants that it must keep."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.timeaxis import OPEN_END, covers, overlaps
from ..operators.slabs import over_slabs, slab_layout, slab_of


def mask_closure(versions: DataFrame, tt: int | None) -> DataFrame:
    """Hide belief ends that come after the pinned time: they were not known then."""
    if tt is None:
        return versions
    return versions.withColumn("tt_e", F.when(F.col("tt_e") > tt, F.lit(OPEN_END)).otherwise(F.col("tt_e")))


def scope(versions: DataFrame, tt: int | None = None) -> DataFrame:
    """Versions believed at ``tt`` (now if None), masked. The comparisons are plain and reach the Parquet scan."""
    if tt is None:
        return versions.where(F.col("tt_e") == OPEN_END)
    return mask_closure(versions.where((F.col("tt_s") <= tt) & (F.col("tt_e") > tt)), tt)


def snapshot(versions: DataFrame, t: int, tt: int | None = None) -> DataFrame:
    """G(t, tt)."""
    return scope(versions, tt).where(covers("vt_s", "vt_e", F.lit(t)))


def public_version(df: DataFrame) -> DataFrame:
    """A version without what tells of the present belief."""
    from ..functions.canon import BELIEF_COLUMNS

    return df.drop(*BELIEF_COLUMNS)


def overlap_violations(versions: DataFrame) -> DataFrame:
    """Pairs of versions of one identity that overlap in valid and in transaction time; a sound store has none.

    Versions meet in the slab of the later start, so an identity of any size is dealt over many tasks and a pair is made once.
    """
    layout = slab_layout(versions, "ident", "vt_s", "vt_e")
    held = over_slabs(versions.select("ident", "vt_s", "vt_e", "tt_s", "tt_e"), layout, "ident", "vt_s", "vt_e").withColumn("own", F.col("slab") == slab_of("vt_s"))
    a, b = held.alias("a"), held.alias("b")
    key = lambda x: F.struct(f"{x}.vt_s", f"{x}.tt_s", f"{x}.vt_e", f"{x}.tt_e")
    # pairs are ordered by start, so the later start is b's
    both = (F.col("a.ident") == F.col("b.ident")) & (F.col("a.slab") == F.col("b.slab")) & F.col("b.own") & (key("a") < key("b"))
    both &= overlaps(F.col("a.vt_s"), F.col("a.vt_e"), F.col("b.vt_s"), F.col("b.vt_e")) & overlaps(F.col("a.tt_s"), F.col("a.tt_e"), F.col("b.tt_s"), F.col("b.tt_e"))
    return a.join(b, both).select(F.col("a.ident").alias("ident"), F.col("a.vt_s").alias("a_vt_s"), F.col("a.tt_s").alias("a_tt_s"), F.col("b.vt_s").alias("b_vt_s"), F.col("b.tt_s").alias("b_tt_s"))


def pinned_digest(versions: DataFrame, tt: int) -> str:
    """Digest of all that was believed at ``tt``; later writes do not change it."""
    from ..functions.canon import store_digest

    return store_digest(public_version(scope(versions, tt)))


def latest_before(events: DataFrame, states: DataFrame, key: str, t: str, value: str) -> DataFrame:
    """As-of join: each event with the last ``value`` of ``states`` of its key strictly before its time; one sort of the union."""
    names = events.columns
    union = events.withColumn("_v", F.lit(None).cast(states.schema[value].dataType)).withColumn("_e", F.lit(True)).unionByName(
        states.select(key, t, F.col(value).alias("_v")).withColumn("_e", F.lit(False)), allowMissingColumns=True
    )
    before = Window.partitionBy(key).orderBy(t).rangeBetween(Window.unboundedPreceding, -1)
    return union.withColumn(value, F.last("_v", ignorenulls=True).over(before)).where("_e").select(*names, value)
