"""Program-made tasks with gold from the engine: 17 templates in three families, planted patterns, and correction probes."""

from __future__ import annotations

import hashlib
import json
import random
from dataclasses import dataclass, field

from pyspark.sql import functions as F

from ..functions.timeaxis import DAY, HOUR
from ..plans.executor import PlanFailure, execute_plan
from ..plans.ir import Plan, ref
from ..plans.store import Store

PARAPHRASES = ("{q}", "Please answer: {q}", "From the graph's records: {q}")


@dataclass
class Task:
    suite: str
    task_id: str
    family: str
    template: str
    prompt: str
    answer_kind: str
    plan: Plan
    gold: object = None
    split: str = ""
    probe_pair: str = ""
    probe_side: str = ""
    needs: dict = field(default_factory=dict)  # what the rule readers of the baselines are asked


def _plan(steps: list[tuple[str, str, dict]], answer: dict) -> Plan:
    return Plan.parse({"steps": [{"id": i, "op": op, "args": a} for i, op, a in steps], "answer": answer})


def templates(p: dict) -> dict[str, tuple[str, str, str, Plan]]:
    """{template: (family, question, kind, plan)} for sampled parameters ``p``."""
    u, v, d, d2, t0, pin = p["u"], p["v"], p["d"], p["d2"], p["t0"], p.get("pin")
    pinned = {"as_of_tt": pin} if pin else {}
    at = lambda ident, day: [("s1", "version_history", {"ident": str(ident), "limit": 1000, **pinned}), ("s2", "compute", {"fn": "filter", "input": ref("s1.rows[*]"), "field": "vt_s", "test": ["<=", day], "limit": 1000}), ("s3", "compute", {"fn": "filter", "input": ref("s2.rows[*]"), "field": "vt_e", "test": [">", day]})]
    window = {"t_from": t0, "t_to": t0 + p["days"] * DAY}
    return {
        "a01": ("T1", f"What was the value of user {u} at time {d}?", "value", _plan(at(u, d), {"from": "s3", "field": "rows[0].w", "kind": "value"})),
        "a02": ("T1", f"How many versions does user {u} have?", "count", _plan([("s1", "version_history", {"ident": str(u), "audit": True, "limit": 1000})], {"from": "s1", "field": "rows_total", "kind": "count"})),
        "a03": ("T1", f"How many nodes lie within two hops of {u} at {d}?", "count", _plan([("s1", "khop_neighbourhood", {"seeds": [u], "k": 2, "t": d, "limit": 1000})], {"from": "s1", "field": "rows_total", "kind": "count"})),
        "a04": ("T1", f"How many users differ between {d} and {d2}?", "count", _plan([("s1", "diff_states", {"t1": d, "t2": d2, "limit": 1000})], {"from": "s1", "field": "rows_total", "kind": "count"})),
        "a05": ("T1", f"How many nodes can {u} reach from {t0} within {p['days']} days?", "count", _plan([("s1", "earliest_arrival", {"sources": [u], **window, "limit": 1000})], {"from": "s1", "field": "rows_total", "kind": "count"})),
        "a06": ("T1", f"When does {u} reach {v} with waits up to a day, from {t0}?", "value", _plan([("s1", "earliest_arrival", {"sources": [u], **window, "max_wait": DAY, "targets": [v]})], {"from": "s1", "field": "rows[0].arrival", "kind": "value"})),
        "a07": ("T1", f"Over which time does the first path from {u} to {v} run, from {t0}?", "interval", _plan([("s1", "time_respecting_paths", {"src": u, "dst": v, **window, "k": 5, "max_hops": 3})], {"from": "s1", "field": "rows[0].arrives", "kind": "interval", "ends": ["departs", "arrives"]})),
        "a08": ("T1", f"How many cyclic triangles within {p['h']} hours?", "count", _plan([("s1", "count_motifs", {"pattern": "cyclic", "delta": p["h"] * HOUR})], {"from": "s1", "field": "rows[0].count", "kind": "count"})),
        "a09": ("T1", f"Which day from {t0} has most edges?", "interval", _plan([("s1", "metric_series", {**window, "width": DAY, "limit": 1000}), ("s2", "compute", {"fn": "topk", "input": ref("s1.rows[*]"), "field": "edges", "k": 1})], {"from": "s2", "field": "rows[0].bucket", "kind": "interval", "ends": ["bucket"], "width": DAY})),
        "a10": ("T1", f"When is the first burst from {t0}?", "interval", _plan([("s1", "detect_bursts", {**window, "width": 6 * HOUR, "rule": "zscore", "lookback": 6, "threshold": 1.5, "only_bursts": True})], {"from": "s1", "field": "rows[0].bucket", "kind": "interval", "ends": ["bucket"], "width": 6 * HOUR})),
        "e01": ("T3", f"Which neighbours did {u} gain from before {d} to after it?", "entity_set", _plan([("s1", "neighbour_changes", {"node": u, "w1": [d - 3 * DAY, d], "w2": [d, d + 3 * DAY]}), ("s2", "compute", {"fn": "filter", "input": ref("s1.rows[*]"), "field": "change", "test": ["=", "gained"]})], {"from": "s2", "field": "rows[*].neighbour", "kind": "entity_set"})),
        "e02": ("T3", f"How many neighbours did {u} lose from before {d} to after it?", "count", _plan([("s1", "neighbour_changes", {"node": u, "w1": [d - 3 * DAY, d], "w2": [d, d + 3 * DAY]}), ("s2", "compute", {"fn": "filter", "input": ref("s1.rows[*]"), "field": "change", "test": ["=", "lost"]})], {"from": "s2", "field": "rows_total", "kind": "count"})),
        "e03": ("T3", f"What is the reciprocity on the third day from {t0}?", "value", _plan([("s1", "metric_series", {**window, "width": DAY})], {"from": "s1", "field": "rows[2].reciprocity", "kind": "value"})),
        "m01": ("T4", f"How many cyclic triangles within {p['h']} hours lie among the nodes that {u} reaches from {t0} in {p['days']} days?", "count", _plan([("s1", "earliest_arrival", {"sources": [u], **window, "limit": 1000}), ("s2", "count_motifs", {"pattern": "cyclic", "delta": p["h"] * HOUR, "nodes": ref("s1.rows[*].node")})], {"from": "s2", "field": "rows[0].count", "kind": "count"})),
        "m02": ("T4", f"What is the greatest value that the user named {u} ever had?", "value", _plan([("s1", "resolve_names", {"text": str(u), "mode": "exact", "types": ["user"]}), ("s2", "version_history", {"ident": ref("s1.rows[0].ident"), "audit": True, "limit": 1000}), ("s3", "compute", {"fn": "max", "input": ref("s2.rows[*]"), "field": "w"})], {"from": "s3", "field": "rows[0].value", "kind": "value"})),
        "m03": ("T4", f"How many of the bursts from {t0} have at least {p['n']} edges?", "count", _plan([("s1", "detect_bursts", {**window, "width": 6 * HOUR, "rule": "median", "lookback": 6, "threshold": 1.2, "only_bursts": True}), ("s2", "compute", {"fn": "filter", "input": ref("s1.rows[*]"), "field": "value", "test": [">=", p["n"]]})], {"from": "s2", "field": "rows_total", "kind": "count"})),
        "m04": ("T4", f"How many clicks of user {u} overlap its purchases?", "count", _plan([("s1", "interval_pairs", {"a": {"kind": "click", "src": u}, "b": {"kind": "purchase", "src": u}, "relations": ["overlaps", "overlapped_by", "during", "contains"], "match": "src", "limit": 1000}), ("s2", "compute", {"fn": "count", "input": ref("s1.rows[*]")})], {"from": "s2", "field": "rows[0].value", "kind": "count"})),
    }


TEMPLATES = ("a01", "a02", "a03", "a04", "a05", "a06", "a07", "a08", "a09", "a10", "e01", "e02", "e03", "m01", "m02", "m03", "m04")


def _gold(task: Task, store: Store, memo: dict):
    """Gold of a task, or None if its plan fails or its answer says nothing."""
    try:
        done = execute_plan(task.plan, store, memo=memo)
        value = done.answer
    except PlanFailure:
        return None
    if any(not s.complete for s in done.steps.values()) or value is None or value == []:
        return None
    if task.answer_kind == "interval":
        row = done.steps[task.plan.answer["from"]].page.rows[0]
        ends = [row[k] for k in task.plan.answer["ends"]]
        return [ends[0], ends[1] if len(ends) > 1 else ends[0] + task.plan.answer["width"]]
    return sorted(map(str, value)) if task.answer_kind == "entity_set" else value


def _ids(store: Store) -> list[int]:
    """Five hundred senders, drawn by a hash from all."""
    return [r[0] for r in store.edges.select("src").distinct().orderBy(F.xxhash64("src"), "src").limit(500).collect()]


def make_tasks(store: Store, suite: str, per_template: int = 2, seed: int = 1, only: tuple[str, ...] = TEMPLATES, memo: dict | None = None) -> list[Task]:
    """Tasks with gold; parameters are drawn from the store, degenerate instances are left out."""
    rnd, users, out = random.Random(seed), _ids(store), []
    memo = {} if memo is None else memo
    for name in only:
        for n in range(per_template):
            t0 = store.stats.t_min // DAY * DAY
            p = {"u": rnd.choice(users), "v": rnd.choice(users), "d": t0 + rnd.randrange(5, 20) * DAY, "t0": t0 + rnd.randrange(0, 5) * DAY, "days": rnd.randrange(3, 8), "h": rnd.choice((3, 6)), "n": rnd.choice((5, 10))}
            p["d2"] = p["d"] + rnd.randrange(1, 5) * DAY
            family, question, kind, plan = templates(p)[name]
            task = Task(suite, f"{suite}-{name}-{n}", family, name, rnd.choice(PARAPHRASES).format(q=question), kind, plan, needs={**p, "template": name})
            task.gold = _gold(task, store, memo)
            if task.gold is not None:
                out.append(task)
    return split_tasks(out)


def make_probe_pairs(store: Store, suite: str, n: int, pin: int, at: int, memo: dict | None = None) -> list[Task]:
    """Pairs of questions on one fact, before and after its correction; only pairs whose golds differ."""
    from ..substrate.snapshots import snapshot

    memo = {} if memo is None else memo
    before = snapshot(store.versions, at, pin).select("ident", F.col("w").alias("was"))
    now = snapshot(store.versions, at).select("ident", F.col("w").alias("is"))
    # hash order spreads the choice; the number of pairs is a parameter of the suite
    users = [r["ident"] for r in before.join(now, "ident").where("was <> is").orderBy(F.xxhash64("ident")).limit(n).collect()]
    out = []
    for u in users:
        pair = []
        for side, tt in (("before", pin), ("current", None)):
            p = {"u": u, "v": 0, "d": at, "d2": at + DAY, "t0": at, "days": 3, "h": 3, "n": 1, "pin": tt}
            _, question, kind, plan = templates(p)["a01"]
            question += f" As believed at {pin}, before the correction." if side == "before" else " As believed now."
            task = Task(suite, f"{suite}-probe-{u}-{side}", "probe", "a01", question, kind, plan, probe_pair=f"{suite}-{u}", probe_side=side, needs={**p, "template": "a01"})
            task.gold = _gold(task, store, memo)
            pair.append(task)
        if all(t.gold is not None for t in pair) and pair[0].gold != pair[1].gold:
            out += pair
    return split_tasks(out)


def make_planted_tasks(store: Store, manifest: list, suite: str = "patterns", memo: dict | None = None) -> list[Task]:
    """One task for each planted structure; gold is the manifest's. Motifs and bursts are looked for in time alone, paths between their ends."""
    planted = store.edges.where("eid < 0")
    begun = {e: t for e, t in planted.select("eid", "t").collect()}  # the manifest's own edges
    out = []
    for pattern_id, kind, nodes, eids in manifest:
        day, last = min(begun[e] for e in eids), max(begun[e] for e in eids)
        if kind == "burst":
            template, gold, question = "p03", [str(day)], f"Which ten minutes from {day - DAY // 2} to {day + 2 * HOUR} had unusually many edges?"
            args = {"t_from": day - DAY // 2, "t_to": day + 2 * HOUR, "width": HOUR // 6, "rule": "zscore", "lookback": 36, "threshold": 8.0, "only_bursts": True}
            plan = _plan([("s1", "detect_bursts", args)], {"from": "s1", "field": "rows[*].bucket", "kind": "entity_set"})
        elif kind == "path":
            template, gold, question = "p02", sorted(map(str, eids)), f"By which edges does the first path from {nodes[0]} to {nodes[-1]} after {day - HOUR} go?"
            args = {"src": nodes[0], "dst": nodes[-1], "t_from": day - HOUR, "t_to": last + HOUR, "k": 1, "max_hops": 3}
            plan = _plan([("s1", "time_respecting_paths", args)], {"from": "s1", "field": "rows[0].eids", "kind": "entity_set"})
        else:
            template, gold, question = "p01", sorted(map(str, eids)), f"Which edges form the first {kind} pattern from {day} to {last}?"
            plan = _plan([("s1", "find_motifs", {"pattern": kind, "delta": HOUR, "t_from": day, "t_to": last + 1})], {"from": "s1", "field": "rows[0].eids", "kind": "entity_set"})
        out.append(Task(suite, f"{suite}-{pattern_id}", "T2", template, question, "entity_set", plan, gold))
    return split_tasks(out)


def split_tasks(tasks: list[Task], dev: float = 0.2) -> list[Task]:
    """20/80 within each family, by the order of a hash of the id."""
    for family in {t.family for t in tasks}:
        mine = sorted((t for t in tasks if t.family == family), key=lambda t: hashlib.sha256(t.task_id.encode()).hexdigest())
        for i, t in enumerate(mine):
            t.split = "dev" if i < round(dev * len(mine)) else "test"
    return tasks


def split_digest(tasks: list[Task]) -> str:
    return hashlib.sha256(json.dumps(sorted((t.task_id, t.split, str(t.gold)) for t in tasks)).encode()).hexdigest()
