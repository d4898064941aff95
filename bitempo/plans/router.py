"""Calling operators in process by their tool schema, and looking at traces."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .executor import Execution, execute_plan, trace_frame
from .guard import CostRefusal, refuse
from .ir import Plan
from .paging import ResultPage
from .store import Store
from .verifier import Violation, check_schema


def call_tool(store: Store, name: str, args: dict) -> ResultPage | CostRefusal | list[Violation]:
    """One operator's page; violations of its schema or a refusal are results, not exceptions."""
    plan = Plan.parse({"steps": [{"id": "call", "op": name, "args": args}], "answer": {"from": "call", "field": "rows_total", "kind": "count"}})
    wrong = check_schema(plan)
    if wrong:
        return wrong
    no = refuse(name, args, store.stats)
    return no if no is not None else execute_plan(plan, store).steps["call"].page


def trace_report(store: Store, executions: dict[str, Execution]) -> DataFrame:
    """(run_id, step_id, op, rows, state, wall_ms, result_digest) of executions, in words for a reader."""
    state = F.when(~F.col("complete"), "cut page").when(F.col("tainted"), "rests on a cut page").otherwise("complete")
    return trace_frame(store, executions).select("run_id", "step_id", "op", F.concat_ws(" of ", "rows_returned", "rows_total").alias("rows"), state.alias("state"), "wall_ms", "result_digest")


def export_trace(store: Store, executions: dict[str, Execution], folder: str) -> None:
    trace_frame(store, executions).write.mode("append").json(folder)
