"""At most three revisions of a plan, each told what was wrong."""

from __future__ import annotations

from dataclasses import dataclass, field

from .ir import Plan
from .store import Store
from .verifier import CHECKS, Violation, verify_plan

BUDGET = 3


@dataclass
class RepairOutcome:
    first_valid: bool
    attempts: int
    plan: Plan | None
    violations: list[Violation] = field(default_factory=list)


def repair_loop(planner, task, store: Store, budget: int = BUDGET, checks: tuple[str, ...] = CHECKS, first: int = 0) -> RepairOutcome:
    """Plans numbered from ``first`` on until one passes the checks, ``budget`` revisions at most."""
    feedback: list[Violation] = []
    for attempt in range(first, first + budget + 1):
        try:
            plan = planner.plan(task, feedback, attempt)
            feedback = verify_plan(plan, task.prompt, store.stats, store.now_tt, checks)
        except (KeyError, TypeError, ValueError) as e:
            plan, feedback = None, [Violation("E_SCHEMA", "", "", str(e))]
        if not feedback:
            return RepairOutcome(attempt == 0, attempt - first + 1, plan)
    return RepairOutcome(False, budget + 1, None, feedback)
