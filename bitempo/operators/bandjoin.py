"""Band and interval joins by slices of time: equi-joins that the planner can hash, with a residual test."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.timeaxis import ALLEN, allen


#: Candidate pairs that a join without an equality may look at.
THETA_BUDGET = 1_000_000_000


def slice_of(t: Column | str, width: int) -> Column:
    t = F.col(t) if isinstance(t, str) else t
    return F.floor(t / F.lit(width)).cast("long")


def band_join(earlier: DataFrame, later: DataFrame, keys: list[str], width: int, t_earlier: str, t_later: str, extra: Column | None = None) -> DataFrame:
    """Pairs of equal keys with 0 <= t_later - t_earlier <= width.

    The earlier side is put into its own slice and the next one, the later side stays in its own, so each pair meets once.
    """
    slices = F.explode(F.array(slice_of(t_earlier, max(1, width)), slice_of(t_earlier, max(1, width)) + 1))
    a = earlier.withColumn("_slice", slices)
    b = later.withColumn("_slice", slice_of(t_later, max(1, width)))
    gap = F.col(t_later) - F.col(t_earlier)
    found = a.join(b, [*keys, "_slice"]).where((gap >= 0) & (gap <= width))
    return (found if extra is None else found.where(extra)).drop("_slice")


def salted_join(left: DataFrame, right: DataFrame, keys: list[str], salts: int) -> DataFrame:
    """Equi-join with the left side dealt over ``salts`` parts of each key and the right side repeated in each, for hub keys."""
    salt = F.pmod(F.xxhash64(*[F.col(c) for c in left.columns]), F.lit(salts)).cast("int")
    a = left.withColumn("_salt", salt)
    b = right.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [*keys, "_salt"]).drop("_salt")


def theta_join(a: DataFrame, b: DataFrame, test: Column, budget: int = THETA_BUDGET) -> DataFrame:
    """Pairs that pass a test which has no equality in it; refused if there are more than ``budget`` candidates."""
    candidates = a.count() * b.count()
    if candidates > budget:
        raise ValueError(f"{candidates} candidate pairs exceed {budget}: add a match key")
    return a.join(b, test)


def interval_join(a: DataFrame, b: DataFrame, keys: list[str], relations: tuple[str, ...], width: int, budget: int = THETA_BUDGET) -> DataFrame:
    """Pairs of intervals (a_s, a_e) and (b_s, b_e) of equal keys in one of the ``relations``, with their relation.

    Relations that touch or share time meet in the slice of the later start, to which each side is repeated over its own slices; so a
    pair meets in one slice alone and nothing is made distinct. Later starts lie among the other side's starts, so a side's slices are cut to
    their extent, and an open interval takes no more of them than that. ``before`` and ``after`` join on the keys and can be as large as all
    pairs; without keys they are made only if their number of candidates, which is counted, is within ``budget``.
    """
    relation = allen("a_s", "a_e", "b_s", "b_e")
    near = tuple(r for r in relations if r not in ("before", "after"))
    far = tuple(r for r in relations if r in ("before", "after"))
    out = None
    if near:
        def sliced(df: DataFrame, s: str, e: str, lo: int | None, hi: int | None) -> DataFrame:
            # an end touches the slice that begins at it, for meets and met_by
            begin, end = F.greatest(F.col(s), F.lit(lo).cast("long")), F.least(F.col(e), F.greatest(F.col(s), F.lit(hi).cast("long")))
            return df.where(begin <= end).withColumn("_slice", F.explode(F.sequence(slice_of(begin, width), slice_of(end, width))))

        ends = lambda df, s: df.agg(F.min(s), F.max(s)).first()
        pairs = sliced(a, "a_s", "a_e", *ends(b, "b_s")).join(sliced(b, "b_s", "b_e", *ends(a, "a_s")), [*keys, "_slice"])
        pairs = pairs.where(F.col("_slice") == slice_of(F.greatest("a_s", "b_s"), width)).drop("_slice")
        out = pairs.withColumn("relation", relation).where(F.col("relation").isin(*near))
    if far:
        test = {"before": F.col("a_e") < F.col("b_s"), "after": F.col("b_e") < F.col("a_s")}
        both = test[far[0]] if len(far) == 1 else test["before"] | test["after"]
        pairs = a.join(b, keys).where(both) if keys else theta_join(a, b, both, budget)
        pairs = pairs.withColumn("relation", relation)
        out = pairs if out is None else out.unionByName(pairs)
    return out


def relation_totals(a: DataFrame, b: DataFrame, keys: list[str]) -> DataFrame:
    """(keys…, before, after): numbers of far pairs without making them, from ranks of ends among starts; one sort of the union."""
    from pyspark.sql import Window

    # an ``a`` end is before all ``b`` starts above it; a ``b`` end is before all ``a`` starts above it
    rows = [
        a.select(*keys, F.col("a_e").alias("at"), F.lit("ea").alias("what")), b.select(*keys, F.col("b_s").alias("at"), F.lit("sb").alias("what")),
        b.select(*keys, F.col("b_e").alias("at"), F.lit("eb").alias("what")), a.select(*keys, F.col("a_s").alias("at"), F.lit("sa").alias("what")),
    ]
    union = rows[0]
    for r in rows[1:]:
        union = union.unionByName(r)
    above = Window.partitionBy(*keys).orderBy("at").rangeBetween(1, Window.unboundedFollowing)
    counted = union.withColumn("sb", F.sum((F.col("what") == "sb").cast("long")).over(above)).withColumn("sa", F.sum((F.col("what") == "sa").cast("long")).over(above))
    return counted.groupBy(*keys).agg(F.coalesce(F.sum(F.when(F.col("what") == "ea", F.col("sb"))), F.lit(0)).alias("before"), F.coalesce(F.sum(F.when(F.col("what") == "eb", F.col("sa"))), F.lit(0)).alias("after"))


__all__ = ["ALLEN", "band_join", "interval_join", "relation_totals", "salted_join", "slice_of", "theta_join"]
