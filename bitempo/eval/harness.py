"""Experiments: systems over suites, ablations, sweeps. Everything is seeded; all systems get the same tasks and budget."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from ..agents.clients import NoisyPlanner, NoisyReporter, ScriptedPlanner, ScriptedReporter
from ..claims.verifier import answer_level, check_claims, gate
from ..plans.executor import PlanFailure, execute_plan
from ..plans.repair import repair_loop
from ..plans.store import Store
from ..plans.verifier import CHECKS
from .scoring import correct, support_report
from .tasks import Task


@dataclass
class System:
    """The full system and its ablations by switches."""

    name: str = "full"
    planner: object = None
    reporter: object = None
    gated: bool = True
    checks: tuple[str, ...] = CHECKS
    taint: bool = True
    budget: int = 3
    keep_pin: bool = True
    spend: bool = False  # plans that fail at run time are made again, untold why, until the budget of generations is spent


def run_task(task: Task, store: Store, system: System, memo: dict | None = None) -> dict:
    row = {"system": system.name, "task": task.task_id, "family": task.family, "suite": task.suite, "side": task.probe_side, "correct": False, "emitted": False, "measured": False, "unsupported": False, "valid_first": False, "executed": False, "answer": None}
    planner = system.planner or ScriptedPlanner()
    plan = repair_loop(planner, task, store, system.budget, system.checks)
    row["valid_first"], row["generations"] = plan.first_valid, plan.attempts
    while True:
        if plan.plan is None:
            return row
        try:
            done = execute_plan(plan.plan, store, system.taint, memo=memo)
            answer = (system.reporter or ScriptedReporter()).report(task, done)
            break
        except (PlanFailure, IndexError, KeyError, TypeError):
            if not system.spend or row["generations"] > system.budget:
                return row
            plan = repair_loop(planner, task, store, 0, system.checks, row["generations"])
            row["generations"] += 1
    row["executed"] = True
    verdicts = check_claims(answer, done, store, system.taint)
    final = answer
    if system.gated:
        final = gate(answer, verdicts).answer
        verdicts = check_claims(final, done, store, system.taint) if final else []
    if final is None:
        return row
    row |= {"emitted": True, "measured": True, "answer": final.value, "unsupported": answer_level(verdicts) == "unsupported", "correct": correct(task.answer_kind, final.value, task.gold)}
    return row


def run_suite(tasks: list[Task], store: Store, system: System) -> list[dict]:
    memo: dict = {}
    return [run_task(t, store, system, memo) for t in tasks]


def run_baseline(tasks: list[Task], name: str, answer: Callable[[Task], object]) -> list[dict]:
    out = []
    for t in tasks:
        value = answer(t)
        out.append({"system": name, "task": t.task_id, "family": t.family, "suite": t.suite, "side": t.probe_side, "correct": correct(t.answer_kind, value, t.gold), "emitted": value is not None, "measured": False, "unsupported": False, "valid_first": False, "executed": value is not None, "answer": value})
    return out


def ablations(tasks: list[Task], store: Store, rates: dict[str, float], reporter_rate: float = 0.1, seed: int = 1) -> dict[str, dict]:
    """Full system, no gate, no output contracts (also with all generations spent), no taint and constrained plans under the same noise."""
    base = dict(reporter=NoisyReporter(reporter_rate, seed))
    planner = lambda constrained=False: NoisyPlanner(rates, seed, constrained=constrained)
    systems = [
        System("full", planner(), **base), System("no_gate", planner(), gated=False, **base), System("no_output_contracts", planner(), checks=tuple(c for c in CHECKS if c != "E_FIELD"), **base),
        System("no_output_contracts_equal_budget", planner(), checks=tuple(c for c in CHECKS if c != "E_FIELD"), spend=True, **base),
        System("no_taint", planner(), taint=False, **base), System("constrained_plans", planner(True), **base),
    ]
    return {s.name: support_report(run_suite(tasks, store, s)) for s in systems}


def planner_sweep(tasks: list[Task], store: Store, levels: tuple[float, ...] = (0.0, 0.1, 0.3), seed: int = 1) -> dict[float, dict]:
    """Accuracy as the planner's error rates rise; the rate of unsupported answers stays zero behind the gate."""
    from ..agents.clients import PLAN_ERRORS

    return {x: support_report(run_suite(tasks, store, System("full", NoisyPlanner({k: x for k in PLAN_ERRORS}, seed, repair=0.5), NoisyReporter(x, seed)))) for x in levels}
