"""Claims against evidence: each is supported, weakly supported or unsupported, for a stated reason."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.timeaxis import ALLEN, allen
from ..plans.executor import Execution, PlanFailure, StepResult, lookup
from ..plans.ir import Ref
from ..plans.paging import digest_rows
from ..plans.registry import REGISTRY

KINDS = ("count", "value", "entity", "ordering", "pattern")
GATED = ("count", "value", "entity", "ordering")
LEVELS = ("unsupported", "weak", "supported")
TOLERANCE = 1e-9


@dataclass(frozen=True)
class Claim:
    kind: str
    value: object  # a number, a list of identifiers, (a, b, relation) or a digest
    cites: tuple[str, ...]
    field: str | None = None  # where a number stands in a cited step
    pointer: str | None = None  # a step named as the source; it must be cited


@dataclass
class Answer:
    kind: str
    value: object
    claims: list[Claim] = field(default_factory=list)

    def with_claims(self, claims: list[Claim]) -> "Answer":
        return replace(self, claims=claims)


@dataclass(frozen=True)
class Verdict:
    claim: int
    kind: str
    level: str
    reason: str


def relation_of(a: tuple[int, int], b: tuple[int, int]) -> str:
    """Allen's relation of two half-open intervals, by comparing their ends."""
    (s, e), (x, y) = a, b
    if e <= x:
        return "meets" if e == x else "before"
    if y <= s:
        return "met_by" if y == s else "after"
    left, right = (s > x) - (s < x), (e > y) - (e < y)
    return {(0, 0): "equals", (0, -1): "starts", (0, 1): "started_by", (1, 0): "finishes", (-1, 0): "finished_by", (1, -1): "during", (-1, 1): "contains", (-1, -1): "overlaps", (1, 1): "overlapped_by"}[left, right]


def _numbers_equal(a, b) -> bool:
    return isinstance(a, (int, float)) and isinstance(b, (int, float)) and not isinstance(a, bool) and abs(a - b) <= TOLERANCE


def identifiers(value) -> set[str]:
    """Every identifier in a page's rows, at any depth."""
    if isinstance(value, dict):
        return {x for v in value.values() for x in identifiers(v)}
    if isinstance(value, (list, tuple)):
        return {x for v in value for x in identifiers(v)}
    return set() if value is None or isinstance(value, (bool, float)) else {str(value)}


def _at(execution: Execution, step: StepResult, where: str | None):
    try:
        return lookup(execution.steps, Ref.parse(f"{step.id}.{where or 'rows_total'}"))
    except PlanFailure:
        return None


def _grounded(claim: Claim, execution: Execution, step: StepResult) -> bool:
    if claim.kind in ("count", "value"):
        return _numbers_equal(_at(execution, step, claim.field), claim.value)
    if claim.kind == "entity":
        return {str(v) for v in claim.value} <= identifiers(step.page.rows)
    if claim.kind == "ordering":
        a, b, relation = claim.value
        known = identifiers(step.page.rows)
        return relation in ALLEN and all(str(x) in known for x in (*a, *b)) and relation_of(tuple(a), tuple(b)) == relation
    return False


def check_claim(claim: Claim, execution: Execution, store=None, taint: bool = True) -> tuple[str, str]:
    cited = [execution.steps[c] for c in claim.cites if c in execution.steps]
    if claim.pointer is not None and claim.pointer not in claim.cites:
        return "unsupported", "points to an uncited step"
    if not cited:
        return "unsupported", "cites no step of the trace"
    if claim.kind == "pattern":
        step = cited[0]
        again = REGISTRY[step.op].run(store, {k: v for k, v in step.args.items() if k not in ("limit", "cursor")}) if store is not None else None
        rows = [r.asDict(recursive=True) for r in again.orderBy(*REGISTRY[step.op].order).limit(step.page.rows_returned).collect()] if again is not None else step.page.rows
        if digest_rows(rows) != claim.value:
            return "unsupported", "a new run has another digest"
    elif not any(_grounded(claim, execution, s) for s in cited):
        return "unsupported", "not in the cited evidence"
    if taint and any(not s.complete or s.tainted for s in cited):
        return "weak", "the evidence is incomplete"
    return "supported", ""


def check_claims(answer: Answer, execution: Execution, store=None, taint: bool = True) -> list[Verdict]:
    return [Verdict(i, c.kind, *check_claim(c, execution, store, taint)) for i, c in enumerate(answer.claims)]


def answer_level(verdicts: list[Verdict]) -> str:
    """The least level of the gated claims; supported if there are none."""
    return min((v.level for v in verdicts if v.kind in GATED), key=LEVELS.index, default="supported")


@dataclass
class GatedAnswer:
    answer: Answer | None
    dropped: list[int]


def gate(answer: Answer, verdicts: list[Verdict]) -> GatedAnswer:
    """Claims that are rejected go; without a gated claim left there is no answer."""
    dropped = [v.claim for v in verdicts if v.kind in GATED and v.level == "unsupported"]
    kept = [c for i, c in enumerate(answer.claims) if i not in dropped]
    emits = any(c.kind in GATED for c in kept)
    return GatedAnswer(answer.with_claims(kept) if emits else None, dropped)


def check_claims_table(claims: DataFrame, evidence: DataFrame) -> DataFrame:
    """Verdicts of many answers at once: (run_id, answer_id, claim_id, kind, level).

    ``claims(run_id, answer_id, claim_id, kind, cites, pointer, number, ids)`` meets ``evidence(run_id, step_id, number, ids, complete, tainted)`` by
    one equi-join on run and step; the best cited step decides and any incomplete one lowers it. No driver loop. Orderings are claims with
    ``a_s, a_e, b_s, b_e, relation`` whose ends are among the evidence's ``ids``; patterns are claims with a ``digest`` that must be that of the evidence.
    Where a side has no such columns, claims of these kinds have nothing to stand on.
    """
    extra = {"a_s": "long", "a_e": "long", "b_s": "long", "b_e": "long", "relation": "string", "digest": "string"}
    claims = claims.withColumns({c: F.lit(None).cast(t) for c, t in extra.items() if c not in claims.columns})
    evidence = evidence if "digest" in evidence.columns else evidence.withColumn("digest", F.lit(None).cast("string"))
    cited = claims.withColumn("step_id", F.explode("cites"))
    met = cited.join(evidence.select("run_id", "step_id", F.col("number").alias("seen"), F.col("ids").alias("known"), F.col("digest").alias("seen_digest"), (~F.col("complete") | F.col("tainted")).alias("partial")), ["run_id", "step_id"], "left")
    number = F.coalesce(F.abs(F.col("number") - F.col("seen")) <= TOLERANCE, F.lit(False))
    entity = F.coalesce(F.size(F.array_except("ids", "known")) == 0, F.lit(False))
    ends = F.array(*[F.col(c).cast("string") for c in ("a_s", "a_e", "b_s", "b_e")])
    ordering = F.coalesce((F.size(F.array_except(ends, "known")) == 0) & (allen("a_s", "a_e", "b_s", "b_e") == F.col("relation")), F.lit(False))
    pattern = F.coalesce(F.col("digest") == F.col("seen_digest"), F.lit(False))
    ok = F.when(F.col("kind") == "entity", entity).when(F.col("kind") == "ordering", ordering).when(F.col("kind") == "pattern", pattern).otherwise(number)
    per = met.groupBy("run_id", "answer_id", "claim_id", "kind").agg(F.bool_or(ok).alias("ok"), F.bool_or(F.coalesce("partial", F.lit(False))).alias("partial"), F.bool_or(F.col("pointer").isNull() | (F.col("pointer") == F.col("step_id"))).alias("pointed"))
    level = F.when(~F.col("ok") | ~F.col("pointed"), "unsupported").when(F.col("partial"), "weak").otherwise("supported")
    return per.select("run_id", "answer_id", "claim_id", "kind", level.alias("level"))
