"""The plan language: a JSON graph of operator calls, references without expressions, and the place of the answer."""

from __future__ import annotations

import json
import re
from dataclasses import dataclass, field

_REF = re.compile(r"^(?P<step>[A-Za-z_]\w*)\.(?:rows\[(?P<at>\d+|\*)\](?:\.(?P<row_field>[A-Za-z_]\w*))?|(?P<page_field>[A-Za-z_]\w*))$")


@dataclass(frozen=True)
class Ref:
    step: str
    at: str | None = None  # a row's number or "*"
    field: str | None = None

    @classmethod
    def parse(cls, text: str) -> "Ref | None":
        m = _REF.match(text) if isinstance(text, str) else None
        return None if m is None else cls(m["step"], m["at"], m["row_field"] or m["page_field"])

    @property
    def star(self) -> bool:
        return self.at == "*"


@dataclass
class Step:
    id: str
    op: str
    args: dict


@dataclass
class Plan:
    steps: list[Step] = field(default_factory=list)
    answer: dict = field(default_factory=dict)  # from, field, kind

    @classmethod
    def parse(cls, text: str | dict) -> "Plan":
        raw = json.loads(text) if isinstance(text, str) else text
        return cls([Step(s["id"], s["op"], dict(s.get("args") or {})) for s in raw["steps"]], dict(raw["answer"]))

    def to_json(self) -> str:
        return json.dumps({"plan_version": 1, "steps": [{"id": s.id, "op": s.op, "args": s.args} for s in self.steps], "answer": self.answer}, sort_keys=True)

    def step(self, ident: str) -> Step | None:
        return next((s for s in self.steps if s.id == ident), None)


def ref(text: str) -> dict:
    return {"$ref": text}


def refs_in(value, path: str = "") -> list[tuple[str, str]]:
    """(path, text) of every reference inside an argument."""
    if isinstance(value, dict):
        if set(value) == {"$ref"}:
            return [(path, value["$ref"])]
        return [x for k, v in value.items() for x in refs_in(v, f"{path}.{k}" if path else k)]
    if isinstance(value, list):
        return [x for i, v in enumerate(value) for x in refs_in(v, f"{path}[{i}]")]
    return []


def drop_pin(plan: Plan) -> Plan:
    """The same plan over the present belief: the control for wrong belief states."""
    return Plan([Step(s.id, s.op, {k: v for k, v in s.args.items() if k != "as_of_tt"}) for s in plan.steps], dict(plan.answer))


def topological(plan: Plan) -> list[Step] | None:
    """Steps in an order that respects references; None if they form a cycle."""
    left, done, out = list(plan.steps), set(), []
    known = {s.id for s in plan.steps}
    while left:
        ready = [s for s in left if all((r := Ref.parse(t)) is None or r.step in done or r.step not in known for _, t in refs_in(s.args))]
        if not ready:
            return None
        out += ready
        done |= {s.id for s in ready}
        left = [s for s in left if s.id not in done]
    return out
