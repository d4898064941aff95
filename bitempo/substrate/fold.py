"""Sequential belief: fold every identity's operations, in order, into versions and outcomes.

An operation touches the live pieces that it overlaps; they close at its transaction time and what it leaves of them reopens.
``assert`` and ``correct`` add a piece of their own, ``correct`` asks for something to correct and ``retract`` cuts all believed valid time from
its start on. The fold is one higher-order aggregate over an identity's sorted operations, in the JVM.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.timeaxis import OPEN_END

FAILURES = ("F_EMPTY_INTERVAL", "F_NOTHING_TO_CORRECT", "F_NOTHING_TO_RETRACT")
_PIECE = "struct<vt_s:bigint,vt_e:bigint,tt_s:bigint,w:double>"
_CLOSED = "struct<vt_s:bigint,vt_e:bigint,tt_s:bigint,tt_e:bigint,w:double>"
_STATE = f"struct<live:array<{_PIECE}>,closed:array<{_CLOSED}>,outcomes:array<struct<batch_id:bigint,seq:int,code:string>>>"


def _piece(vt_s: Column, vt_e: Column, tt_s: Column, w: Column) -> Column:
    return F.struct(vt_s.alias("vt_s"), vt_e.alias("vt_e"), tt_s.alias("tt_s"), w.alias("w"))


def _step(state: Column, o: Column, require_existing: bool) -> Column:
    live, start = state["live"], o["vt_s"]
    end = F.when(o["op"] == "retract", F.lit(OPEN_END)).otherwise(o["vt_e"])
    hit = lambda p: (p["vt_s"] < end) & (p["vt_e"] > start)
    none = ~F.exists(live, hit)
    code = F.when((o["op"] != "retract") & (o["vt_s"] >= o["vt_e"]), FAILURES[0]).when((o["op"] == "retract") & none, FAILURES[2])
    if require_existing:
        code = code.when((o["op"] == "correct") & none, FAILURES[1])
    fine = code.isNull() & ~o["void"]
    touched = F.filter(live, hit)
    left = F.flatten(
        F.transform(
            touched,
            lambda p: F.filter(F.array(_piece(p["vt_s"], F.least(p["vt_e"], start), o["tt"], p["w"]), _piece(F.greatest(p["vt_s"], end), p["vt_e"], o["tt"], p["w"])), lambda q: q["vt_s"] < q["vt_e"]),
        )
    )
    own = F.when(o["op"] == "retract", F.array().cast(f"array<{_PIECE}>")).otherwise(F.array(_piece(o["vt_s"], o["vt_e"], o["tt"], o["w"])))
    closed = F.transform(touched, lambda p: F.struct(p["vt_s"].alias("vt_s"), p["vt_e"].alias("vt_e"), p["tt_s"].alias("tt_s"), o["tt"].alias("tt_e"), p["w"].alias("w")))
    outcome = F.struct(o["batch_id"].alias("batch_id"), o["seq"].alias("seq"), code.alias("code"))
    return F.struct(
        F.when(fine, F.concat(F.filter(live, lambda p: ~hit(p)), left, own)).otherwise(live).alias("live"),
        F.when(fine, F.concat(state["closed"], closed)).otherwise(state["closed"]).alias("closed"),
        F.concat(state["outcomes"], F.array(outcome)).alias("outcomes"),
    ).cast(_STATE)


def fold_identities(ops: DataFrame, require_existing: bool = True, void: str | None = None) -> DataFrame:
    """(ident, state) of stamped operations; those whose ``void`` column is true are judged but not applied."""
    row = F.struct("tt", "batch_id", "seq", "op", "vt_s", "vt_e", F.col("w").cast("double").alias("w"), (F.col(void) if void else F.lit(False)).alias("void"))
    grouped = ops.groupBy("ident").agg(F.sort_array(F.collect_list(row)).alias("ops"))
    empty = F.from_json(F.lit('{"live":[],"closed":[],"outcomes":[]}'), _STATE)
    return grouped.select("ident", F.aggregate("ops", empty, lambda s, o: _step(s, o, require_existing)).alias("state"))


def version_id(shard: Column | str = "ident") -> Column:
    """Content id of a version: the whole key takes part, with lengths, so that no two keys share an id."""
    parts = [F.col(c).cast("string") for c in ("ident", "vt_s", "vt_e", "tt_s")] + [F.coalesce(F.col("w").cast("string"), F.lit("~"))]
    return F.sha2(F.concat_ws("|", *[F.concat(F.length(p).cast("string"), F.lit(":"), p) for p in parts]), 256)


def versions_of(folded: DataFrame) -> DataFrame:
    """(version_id, ident, vt_s, vt_e, tt_s, tt_e, w, source, provenance_ref) of folded identities, closed and open."""
    now_open = F.transform("state.live", lambda p: F.struct(p["vt_s"].alias("vt_s"), p["vt_e"].alias("vt_e"), p["tt_s"].alias("tt_s"), F.lit(OPEN_END).alias("tt_e"), p["w"].alias("w")))
    rows = folded.select("ident", F.explode(F.concat("state.closed", now_open)).alias("v")).select("ident", "v.*")
    return rows.select(version_id().alias("version_id"), "*", F.lit(None).cast("string").alias("source"), F.lit(None).cast("string").alias("provenance_ref"))


def fold_versions(ops: DataFrame, require_existing: bool = True) -> DataFrame:
    return versions_of(fold_identities(ops, require_existing))


def fold_in_batches(ops: DataFrame, require_existing: bool = True) -> DataFrame:
    """Versions (ident, vt_s, vt_e, tt_s, tt_e, w) for identities with very long histories, folded outside the JVM.

    Operations of an identity come sorted; the live pieces are all that a step needs, so they are kept in a list that is cut in place.
    """
    import pandas as pd

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        rows, live = [], []
        for r in frame.sort_values(["tt", "batch_id", "seq"]).itertuples(index=False):
            end = OPEN_END if r.op == "retract" else r.vt_e
            touched = [p for p in live if p[0] < end and p[1] > r.vt_s]
            if (r.op != "retract" and r.vt_s >= r.vt_e) or (r.op == "correct" and require_existing and not touched):
                continue
            live = [p for p in live if not (p[0] < end and p[1] > r.vt_s)]
            for s, e, tt, w in touched:
                rows.append((r.ident, s, e, tt, r.tt, w))
                live += [(a, b, r.tt, w) for a, b in ((s, min(e, r.vt_s)), (max(s, end), e)) if a < b]
            if r.op != "retract":
                live.append((r.vt_s, r.vt_e, r.tt, r.w))
        rows += [(frame["ident"].iloc[0], s, e, tt, OPEN_END, w) for s, e, tt, w in live]
        return pd.DataFrame(rows, columns=["ident", "vt_s", "vt_e", "tt_s", "tt_e", "w"])

    return ops.groupBy("ident").applyInPandas(run, "ident string, vt_s long, vt_e long, tt_s long, tt_e long, w double")


def outcomes_of(folded: DataFrame) -> DataFrame:
    return folded.select("ident", F.explode("state.outcomes").alias("o")).select("ident", "o.batch_id", "o.seq", "o.code")


def decide_outcomes(ops: DataFrame, require_existing: bool = True, rounds: int = 50) -> DataFrame:
    """(batch_id, outcome, fail_code): a batch commits only if all its operations do.

    Batches may span identities, so a failure on one identity voids operations on others. The fold is repeated with the failures
    found so far void until they no longer change; in round k at least the first k batches that can still change are
    settled, so the result is that of writing one batch after the other.
    """
    from ..lineage import cut

    known = None
    judged = ops.withColumn("void", F.lit(False))
    for _ in range(rounds):
        codes = outcomes_of(fold_identities(judged, require_existing, "void"))
        result = cut(codes.groupBy("batch_id").agg(F.min("code").alias("fail_code")))
        failed = result.where("fail_code is not null").select("batch_id")
        state = tuple(failed.agg(F.count(F.lit(1)), F.sum(F.xxhash64("batch_id").cast("decimal(38,0)"))).first())
        if state == known:
            return result.select("batch_id", F.when(F.col("fail_code").isNull(), "committed").otherwise("failed").alias("outcome"), "fail_code")
        known = state
        judged = ops.join(failed.withColumn("void", F.lit(True)), "batch_id", "left").withColumn("void", F.coalesce("void", F.lit(False)))
    raise RuntimeError(f"outcomes did not settle in {rounds} rounds")
