"""Deterministic execution of a checked plan into a content-addressed trace with completeness and taint."""

from __future__ import annotations

import hashlib
import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame

from .ir import Plan, Ref, refs_in, topological
from .paging import DEFAULT_LIMIT, ResultPage, canonical_json, page
from .registry import REGISTRY
from .store import Store


class PlanFailure(Exception):
    """A step that could not run: a reference to nothing, or an argument of the wrong shape."""


@dataclass
class StepResult:
    id: str
    op: str
    args: dict  # with references resolved, frames named by their digest
    page: ResultPage
    args_digest: str
    complete: bool
    tainted: bool
    wall_ms: int = 0
    frame: DataFrame | None = None


@dataclass
class Execution:
    plan: Plan
    steps: dict[str, StepResult] = field(default_factory=dict)

    @property
    def answer(self):
        spec = self.plan.answer
        return lookup(self.steps, Ref.parse(f"{spec['from']}.{spec['field']}"))

    def trace_rows(self, run_id: str) -> list[tuple]:
        return [(run_id, s.id, s.op, canonical_json(s.args), s.args_digest, s.page.result_digest, s.page.rows_returned, s.page.rows_total, s.complete, s.tainted, s.wall_ms) for s in self.steps.values()]


TRACE = "run_id string, step_id string, op string, args_json string, args_digest string, result_digest string, rows_returned long, rows_total long, complete boolean, tainted boolean, wall_ms long"


def lookup(steps: dict[str, StepResult], r: Ref):
    """The value that a reference names: a page's field, a row's field, or a list of them."""
    if r is None or r.step not in steps:
        raise PlanFailure(f"no such step: {r}")
    p = steps[r.step].page
    if r.at is None:
        if not hasattr(p, r.field):
            raise PlanFailure(f"no such field: {r.field}")
        return getattr(p, r.field)
    rows = p.rows
    if r.star:
        if rows and r.field is not None and r.field not in rows[0]:
            raise PlanFailure(f"no such field: {r.field}")
        return rows if r.field is None else [x[r.field] for x in rows]
    if int(r.at) >= len(rows):
        raise PlanFailure(f"no row {r.at}")
    row = rows[int(r.at)]
    if r.field is not None and r.field not in row:
        raise PlanFailure(f"no such field: {r.field}")
    return row if r.field is None else row[r.field]


def _resolve(value, steps: dict[str, StepResult]):
    if isinstance(value, dict):
        if set(value) == {"$ref"}:
            return lookup(steps, Ref.parse(value["$ref"]))
        return {k: _resolve(v, steps) for k, v in value.items()}
    if isinstance(value, list):
        return [_resolve(v, steps) for v in value]
    return value


def execute_plan(plan: Plan, store: Store, taint: bool = True, consume: str = "page", exempt_totals: bool = False, memo: dict | None = None) -> Execution:
    """Run every step once and keep its page.

    ``consume='page'``: dependents read the rows of the page, and a truncated page taints them. ``consume='full'``: star
    references read the whole result as a DataFrame that stays distributed, so nothing is cut and nothing tainted by it.
    """
    done = Execution(plan)
    order = topological(plan)
    if order is None:
        raise PlanFailure("cycle")
    for s in order:
        spec = REGISTRY.get(s.op)
        if spec is None:
            raise PlanFailure(f"no such operator: {s.op}")
        begun = time.time()
        args, named, tainted = {}, {}, False
        for k, v in s.args.items():
            refs = [Ref.parse(t) for _, t in refs_in(v)]
            if any(r is None or r.step not in done.steps for r in refs):
                raise PlanFailure(f"bad reference in {s.id}.{k}")
            role = spec.all_params[k].role if k in spec.all_params else ""
            whole = len(refs) == 1 and refs[0].star and isinstance(v, dict)
            if role in ("rows", "nodes") and whole and consume == "full":
                source = done.steps[refs[0].step]
                args[k] = source.frame if role == "rows" or refs[0].field is None else source.frame.select(refs[0].field).distinct()
                named[k] = f"frame:{source.page.result_digest}:{refs[0].field}"
            elif role == "rows":
                source = done.steps[refs[0].step]
                args[k] = store.spark.createDataFrame([tuple(r[c] for c in source.frame.columns) for r in source.page.rows], source.frame.schema)
                named[k] = f"page:{source.page.result_digest}"
            else:
                args[k] = named[k] = _resolve(v, done.steps)
            for r in refs:
                source = done.steps[r.step]
                exact = r.at is None and r.field == "rows_total" and exempt_totals
                cut_off = not source.complete and consume == "page" and not exact
                tainted |= taint and (cut_off or source.tainted)
        digest = hashlib.sha256(canonical_json([s.op, named, store.digest]).encode()).hexdigest()
        call = {k: v for k, v in args.items() if k not in ("limit", "cursor")}
        if memo is not None and digest in memo:
            frame, got = memo[digest]
        else:
            try:
                frame = spec.run(store, call)
                order_by = [c for c in spec.order] or list(frame.columns)
                got = page(frame, order_by, args.get("limit") or DEFAULT_LIMIT, args.get("cursor"))
            except (KeyError, TypeError, ValueError, AttributeError) as e:
                raise PlanFailure(f"{s.id}: {e}") from e
            if memo is not None:
                memo[digest] = (frame, got)
        done.steps[s.id] = StepResult(s.id, s.op, named, got, digest, got.complete, tainted, int((time.time() - begun) * 1000), frame)
    return done


def trace_frame(store: Store, executions: dict[str, Execution]) -> DataFrame:
    return store.spark.createDataFrame([row for run, e in executions.items() for row in e.trace_rows(run)], TRACE)
