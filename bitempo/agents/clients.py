"""Planners and reporters. No model takes part: rates of errors replace it, so its accuracy is no result of ours."""

from __future__ import annotations

import random
from dataclasses import dataclass, field
from typing import Protocol

from ..claims.verifier import Answer, Claim
from ..plans.executor import Execution
from ..plans.ir import Plan
from ..plans.verifier import Violation


class Planner(Protocol):
    def plan(self, task, feedback: list[Violation], attempt: int) -> Plan: ...


class Reporter(Protocol):
    def report(self, task, execution: Execution) -> Answer: ...


class ScriptedPlanner:
    """The task's own plan."""

    def plan(self, task, feedback, attempt):
        return Plan.parse(task.plan.to_json())


#: Errors of planners, by the check that can see them; ``pin`` and ``meaning`` leave a valid plan with another answer.
PLAN_ERRORS = ("field", "ground", "pin", "unit", "schema", "cycle", "cost", "meaning")


@dataclass
class NoisyPlanner:
    """Makes each kind of error with its rate, and repairs one that the feedback names with chance ``repair``."""

    rates: dict[str, float]
    seed: int = 0
    repair: float = 0.7
    constrained: bool = False  # only plans that fit the schema: errors of form vanish, those of content stay
    made: dict[str, set[str]] = field(default_factory=dict)

    def _chance(self, *key) -> float:
        return random.Random(f"{self.seed}|{'|'.join(map(str, key))}").random()

    def plan(self, task, feedback, attempt):
        codes = {"field": "E_FIELD", "ground": "E_GROUND", "unit": "E_TIME", "schema": "E_SCHEMA", "cycle": "E_CYCLE", "cost": "E_COST"}
        if attempt == 0:
            kinds = [k for k in PLAN_ERRORS if not (self.constrained and k in ("schema", "cycle"))]
            self.made[task.task_id] = {k for k in kinds if self._chance(task.task_id, k) < self.rates.get(k, 0.0)}
        named = {v.code for v in feedback}
        for k in list(self.made[task.task_id]):
            if codes.get(k) in named and self._chance(task.task_id, k, "repair", attempt) < self.repair:
                self.made[task.task_id].discard(k)
        plan = Plan.parse(task.plan.to_json())
        for k in sorted(self.made[task.task_id]):
            plan = self._spoil(plan, k)
        return plan

    def _spoil(self, plan: Plan, kind: str) -> Plan:
        first, last = plan.steps[0], plan.steps[-1]
        if kind == "field":
            plan.answer["field"] = "total_count"
        elif kind == "ground":
            for key in ("ident", "node", "src"):
                if key in first.args and not isinstance(first.args[key], dict):
                    first.args[key] = "987654321" if key == "ident" else 987654321
                    break
            else:
                for key in ("seeds", "sources"):
                    if key in first.args:
                        first.args[key] = [987654321]
        elif kind == "pin":
            for s in plan.steps:
                s.args.pop("as_of_tt", None)
        elif kind == "unit":
            for k in ("t", "t_from", "t_to", "t1", "t2"):
                if isinstance(first.args.get(k), int):
                    first.args[k] //= 1000
        elif kind == "schema":
            first.args["verbose"] = True
        elif kind == "cycle":
            first.args["cursor"] = {"$ref": f"{last.id}.cursor"} if last is not first else {"$ref": f"{first.id}.cursor"}
        elif kind == "cost":
            for s in plan.steps:
                if "delta" in s.args:
                    s.args["delta"] = 10**15
        elif kind == "meaning":
            for k in ("k", "lookback", "delta", "width", "max_wait"):
                if isinstance(first.args.get(k), int) and first.args[k] > 1:
                    first.args[k] = max(1, first.args[k] // 2)
                    break
            else:
                for k in ("t_to", "t2"):
                    if isinstance(first.args.get(k), int):
                        first.args[k] -= 86_400_000_000
        return plan


def _claims(task, execution: Execution, value) -> list[Claim]:
    spec = execution.plan.answer
    step, where = spec["from"], spec["field"]
    if task.answer_kind == "entity_set":
        return [Claim("entity", [str(v) for v in value], (step,), pointer=step)]
    if task.answer_kind == "interval":
        row = execution.steps[step].page.rows[0]
        keys = spec["ends"]
        return [Claim("value", row[k], (step,), f"rows[0].{k}", step) for k in keys]
    kind = "count" if task.answer_kind == "count" else "value"
    out = [Claim(kind, value, (step,), where, step)]
    return out


class ScriptedReporter:
    """States what the trace holds, with one claim for each stated figure."""

    def report(self, task, execution):
        spec = execution.plan.answer
        value = execution.answer
        if task.answer_kind == "interval":
            row = execution.steps[spec["from"]].page.rows[0]
            ends = [row[k] for k in spec["ends"]]
            value = [ends[0], ends[1] if len(ends) > 1 else ends[0] + spec["width"]]
        return Answer(task.answer_kind, value, _claims(task, execution, execution.answer))


@dataclass
class NoisyReporter:
    """Errs in a figure with the given rate."""

    rate: float
    seed: int = 0

    def report(self, task, execution):
        answer = ScriptedReporter().report(task, execution)
        if random.Random(f"{self.seed}|{task.task_id}").random() < self.rate and isinstance(answer.value, (int, float)):
            wrong = answer.value + 1
            return Answer(answer.kind, wrong, [Claim(c.kind, c.value + 1 if isinstance(c.value, (int, float)) else c.value, c.cites, c.field, c.pointer) for c in answer.claims])
        return answer


__all__ = ["NoisyPlanner", "NoisyReporter", "PLAN_ERRORS", "Planner", "Reporter", "ScriptedPlanner", "ScriptedReporter"]
