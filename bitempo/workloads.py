"""Stores over the given tables, and the paper's experiments over them as DataFrames."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .baselines.latest import LatestPattern, LatestTwoHop
from .baselines.retrieval import WINDOW, ChunkRetrieval, read_events, retrieve_for_all
from .claims.verifier import Answer, Claim
from .eval.harness import System, ablations, planner_sweep, run_baseline, run_suite, run_task
from .eval.mutations import CLASSES, false_positives, mutation_report, ordering_answers
from .eval.scoring import correct, support_report
from .eval.tasks import make_planted_tasks, make_probe_pairs, make_tasks
from .functions.timeaxis import DAY, OPEN_END
from .operators.resolve import user_ids
from .plans.executor import execute_plan
from .plans.ir import Plan, ref
from .plans.paging import canonical_json
from .plans.registry import tool_manifest
from .plans.store import Store
from .agents.clients import NoisyReporter, ScriptedReporter
from .sources import corpora
from .substrate.clock import log_shard, stamp_transaction_time
from .substrate.segments import segment_versions

T0 = 1_704_067_200_000_000
VALID_AT, PINNED = T0 + 11 * DAY, T0 + 12 * DAY


def message_store(spark: SparkSession, sf_dir: str) -> Store:
    """Message graph and user beliefs, held once for the many small plans that run over them."""
    edges = corpora.message_edges(spark, sf_dir).persist()
    ops = stamp_transaction_time(corpora.user_beliefs(spark, sf_dir).withColumn("log_shard", log_shard("ident")))
    versions = segment_versions(ops).persist()
    now = ops.agg(F.max("tt")).first()[0] or 0
    return Store(spark, edges, versions, corpora.session_intervals(spark, sf_dir), user_ids(edges), now)


def trade_store(spark: SparkSession, sf_dir: str) -> Store:
    """Trade graph and order beliefs."""
    edges = corpora.trade_edges(spark, sf_dir).persist()
    # operations are read by several parts of their versions; they are held until these are made
    ops = stamp_transaction_time(corpora.order_beliefs(spark, sf_dir).withColumn("log_shard", log_shard("ident"))).persist()
    now, versions = ops.agg(F.max("tt")).first()[0] or 0, segment_versions(ops).persist()
    versions.count()
    ops.unpersist()
    return Store(spark, edges, versions, corpora.session_intervals(spark, sf_dir), user_ids(edges), now)


def _frame(spark: SparkSession, rows: list[dict], schema: str) -> DataFrame:
    names = [c.split()[0] for c in schema.split(", ")]
    return spark.createDataFrame([tuple(r.get(n) for n in names) for r in rows], schema)


SCORES = "system string, task string, family string, suite string, side string, correct boolean, emitted boolean, measured boolean, unsupported boolean, valid_first boolean, executed boolean"


def main_study(spark: SparkSession, sf_dir: str, per_template: int = 1) -> DataFrame:
    """Per-task scores of the full system and the three baselines on one suite, with a perfect planner and readers."""
    store = message_store(spark, sf_dir)
    tasks = make_tasks(store, "messages", per_template)
    rows = run_suite(tasks, store, System())
    for name, reader in (("chunk_retrieval", ChunkRetrieval(store.edges)), ("static_context", LatestTwoHop(store)), ("pattern_query", LatestPattern(store))):
        rows += run_baseline(tasks, name, reader)
    return _frame(spark, rows, SCORES)


def second_corpus_study(spark: SparkSession, sf_dir: str, per_template: int = 1) -> DataFrame:
    """The same on the trade graph and order beliefs: day-granular times with many ties, few nodes with many edges."""
    store = trade_store(spark, sf_dir)
    tasks = make_tasks(store, "trade", per_template, only=("a02", "a03", "a04", "a08", "a09", "e02", "e03", "m02", "m03"))
    rows = run_suite(tasks, store, System())
    for name, reader in (("static_context", LatestTwoHop(store)), ("pattern_query", LatestPattern(store))):
        rows += run_baseline(tasks, name, reader)
    return _frame(spark, rows, SCORES)


def probe_study(spark: SparkSession, sf_dir: str, pairs: int = 13) -> DataFrame:
    """Scores on correction probes: the first halves need the earlier belief, which no baseline keeps."""
    store = message_store(spark, sf_dir)
    tasks = make_probe_pairs(store, "messages", pairs, PINNED, VALID_AT)
    rows = run_suite(tasks, store, System())
    for name, reader in (("chunk_retrieval", ChunkRetrieval(store.edges)), ("static_context", LatestTwoHop(store)), ("pattern_query", LatestPattern(store))):
        rows += run_baseline(tasks, name, reader)
    return _frame(spark, rows, SCORES)


RATES = {"field": 0.35, "ground": 0.1, "unit": 0.1, "schema": 0.1, "cycle": 0.05, "meaning": 0.1}
REPORT = "system string, tasks long, accuracy double, coverage double, emitted long, conditional_accuracy double, measured long, unsupported long, unsupported_rate double, first_validity double, execution_success double"


def ablation_study(spark: SparkSession, sf_dir: str, per_template: int = 1) -> DataFrame:
    store = message_store(spark, sf_dir)
    tasks = make_tasks(store, "messages", per_template)
    return _frame(spark, [{"system": k, **v} for k, v in ablations(tasks, store, RATES).items()], REPORT)


def sweep_study(spark: SparkSession, sf_dir: str, per_template: int = 1) -> DataFrame:
    store = message_store(spark, sf_dir)
    tasks = make_tasks(store, "messages", per_template)
    return _frame(spark, [{"system": f"noise {k}", **v} for k, v in planner_sweep(tasks, store).items()], REPORT)


def gate_study(spark: SparkSession, sf_dir: str, per_template: int = 1, seeds: tuple[int, ...] = (1, 2, 3), rate: float = 0.3) -> DataFrame:
    """(seed, system, …) of erring reporters with and without the gate: what the gate costs in accuracy, and the spread over seeds. Plans are run once."""
    store, memo, rows = message_store(spark, sf_dir), {}, []
    tasks = make_tasks(store, "messages", per_template, memo=memo)
    for seed in seeds:
        for name, gated in (("gate", True), ("no_gate", False)):
            system = System(name, reporter=NoisyReporter(rate, seed), gated=gated)
            rows.append({"seed": seed, "system": name, **support_report([run_task(t, store, system, memo) for t in tasks])})
    return _frame(spark, rows, "seed int, " + REPORT)


def breadth_study(spark: SparkSession, sf_dir: str, grid: tuple[tuple[int, int], ...] = ((1, 256), (2, 256), (20, 256), (20, 24)), per_template: int = 2, pairs: int = 5) -> DataFrame:
    """(k, n, side, tasks, tokens, admitted, recall, correct) of chunk retrieval by its breadth: ``k`` chunks of ``n`` events.

    ``tokens`` are those of the chunks that a task got, ``admitted`` is whether all tasks fit the serving window, ``recall`` the share of the events of the
    users asked about that the chunks state. What does not fit is read all the same, so that breadth alone is judged. All tasks are retrieved in one pass.
    """
    store, memo = message_store(spark, sf_dir), {}
    tasks = make_tasks(store, "messages", per_template, only=("a01", "a02", "e01"), memo=memo) + make_probe_pairs(store, "messages", pairs, PINNED, VALID_AT, memo)
    prompts = spark.createDataFrame([(t.task_id, t.prompt) for t in tasks], "task string, prompt string")
    users = {int(t.needs["u"]) for t in tasks}
    sent = {r["src"]: r["n"] for r in store.edges.where(F.col("src").isin(*users)).groupBy("src").agg(F.count(F.lit(1)).alias("n")).collect()}
    rows = []
    for n in sorted({n for _, n in grid}):
        reader = ChunkRetrieval(store.edges, n=n)
        most = max(k for k, m in grid if m == n)
        found = retrieve_for_all(reader.weights, prompts, most).join(reader.held, "chunk").select("task", "place", "text").collect()  # the tasks' own pages
        for k in sorted(k for k, m in grid if m == n):
            got = {t.task_id: [text for task, place, text in sorted(found) if task == t.task_id and place <= k] for t in tasks}
            for side in sorted({t.probe_side for t in tasks}):
                mine = [t for t in tasks if t.probe_side == side]
                tokens = [-(-sum(map(len, got[t.task_id])) * 65 // 100) for t in mine]
                stated = [sum(e[0] == int(t.needs["u"]) for e in read_events(got[t.task_id])) for t in mine]
                right = [correct(t.answer_kind, reader.read(t, got[t.task_id]), t.gold) for t in mine]
                rows.append({"k": k, "n": n, "side": side, "tasks": len(mine), "tokens": max(tokens), "admitted": max(tokens) <= WINDOW, "recall": round(sum(stated) / max(1, sum(sent.get(int(t.needs["u"]), 0) for t in mine)), 6), "correct": sum(right)})
        reader.weights.unpersist()
        reader.held.unpersist()
    return _frame(spark, rows, "k long, n long, side string, tasks long, tokens long, admitted boolean, recall double, correct long")


def scale_study(spark: SparkSession, sf_dir: str, sizes: tuple[int, ...] = (10_000, 100_000, 1_000_000)) -> DataFrame:
    """(edges, op, rows_total, rows_returned, complete, tokens, wall_ms) of plans over generated stores of growing size, as a planner would see them.

    ``tokens`` are those of the manual, the question and the page that comes back: they stay where they are as the store grows.
    """
    manual, rows, day = len(json.dumps(tool_manifest())), [], T0 + 180 * DAY
    for n in sizes:
        edges = corpora.scale_store(spark, n).persist()
        # every edge is a belief of its pair: true for a week from its time on, and known from then
        versions = edges.select(F.concat_ws(">", "src", "dst", "eid").alias("ident"), F.col("t").alias("vt_s"), (F.col("t") + 7 * DAY).alias("vt_e"), F.col("t").alias("tt_s"), F.lit(OPEN_END).alias("tt_e"), "w").persist()
        store = Store(spark, edges, versions)
        for op, args in (("khop_neighbourhood", {"seeds": [5], "k": 2, "t": day}), ("diff_states", {"t1": day, "t2": day + 30 * DAY}), ("metric_series", {"t_from": T0, "t_to": T0 + 365 * DAY, "width": DAY})):
            plan = Plan.parse({"steps": [{"id": "s1", "op": op, "args": args}], "answer": {"from": "s1", "field": "rows_total", "kind": "count"}})
            step = execute_plan(plan, store).steps["s1"]
            said = manual + len(plan.to_json()) + len(canonical_json(step.page.rows))
            rows.append({"edges": n, "op": op, "rows_total": step.page.rows_total, "rows_returned": step.page.rows_returned, "complete": step.complete, "tokens": -(-said * 65 // 100), "wall_ms": step.wall_ms})
        edges.unpersist()
        versions.unpersist()
    return _frame(spark, rows, "edges long, op string, rows_total long, rows_returned long, complete boolean, tokens long, wall_ms long")


def planted_study(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recovery of planted patterns by scripted plans."""
    base = message_store(spark, sf_dir)
    edges, manifest = corpora.planted(spark, base.edges)
    store = Store(spark, edges.persist(), base.versions, base.intervals, base.names, base.now_tt)
    tasks = make_planted_tasks(store, [tuple(r) for r in manifest.collect()])
    return _frame(spark, run_suite(tasks, store, System()), SCORES)


def fault_study(spark: SparkSession, sf_dir: str, per_template: int = 1, pairs: int = 6) -> DataFrame:
    """(class, cases, detected, without): mutations of right answers and how many the checks see, also without taint."""
    store = message_store(spark, sf_dir)
    memo: dict = {}
    tasks = make_tasks(store, "messages", per_template, memo=memo) + make_probe_pairs(store, "messages", pairs, PINNED, VALID_AT, memo)
    pool = []
    for t in tasks:
        done = execute_plan(t.plan, store, memo=memo)
        pool.append((ScriptedReporter().report(t, done), done))
        if t.template in ("a02",) and (extra := ordering_answers(done, "s1")):
            pool.append((extra, done))
    for u in sorted({int(t.needs["u"]) for t in tasks})[: 2 * per_template]:
        # a count over an earlier step's page: the kind that a cut page makes wrong
        counted = Plan.parse({
            "steps": [{"id": "s1", "op": "earliest_arrival", "args": {"sources": [u], "t_from": T0, "t_to": T0 + 5 * DAY, "limit": 1000}}, {"id": "s2", "op": "compute", "args": {"fn": "count", "input": ref("s1.rows[*]")}}],
            "answer": {"from": "s2", "field": "rows[0].value", "kind": "count"},
        })
        done = execute_plan(counted, store, memo=memo)
        pool.append((Answer("count", done.answer, [Claim("count", done.answer, ("s2",), "rows[0].value", "s2")]), done))
    others = {str(r[0]) for r in store.edges.select("src").distinct().limit(2000).collect()}
    on, off = mutation_report(pool, store, repeats=2, others=others), mutation_report(pool, store, classes=("truncated_count",), repeats=2, mechanism=False)
    rows = [{"class": c, "cases": on[c][0], "detected": on[c][1], "without": off.get(c, (0, None))[1]} for c in CLASSES]
    rows.append({"class": "unmutated", "cases": len(pool), "detected": false_positives(pool, store), "without": None})
    return _frame(spark, rows, "class string, cases long, detected long, without long")


def summary(scores: DataFrame) -> dict[str, dict]:
    rows = [r.asDict() for r in scores.collect()]
    return {s: support_report([r for r in rows if r["system"] == s]) for s in sorted({r["system"] for r in rows})}
