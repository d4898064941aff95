import json

import pytest

from bitempo import workloads
from bitempo.agents.clients import NoisyPlanner, NoisyReporter, ScriptedReporter
from bitempo.claims.verifier import Answer, Claim, answer_level, check_claims, gate
from bitempo.eval.harness import System, run_suite
from bitempo.eval.mutations import mutate
from bitempo.eval.scoring import correct, paired_bootstrap, support_report
from bitempo.eval.tasks import make_probe_pairs, make_tasks, split_digest
from bitempo.functions.timeaxis import DAY, HOUR
from bitempo.plans import guard, paging
from bitempo.plans.executor import PlanFailure, execute_plan
from bitempo.plans.ir import Plan, Ref, drop_pin, ref
from bitempo.plans.registry import REGISTRY, tool_manifest
from bitempo.plans.repair import repair_loop
from bitempo.plans.verifier import verify_plan

T0 = workloads.T0
WINDOW = {"t_from": T0, "t_to": T0 + 5 * DAY}


@pytest.fixture(scope="module")
def store(spark, sf):
    return workloads.message_store(spark, sf)


def plan(*steps, **answer):
    return Plan.parse({"steps": [{"id": i, "op": op, "args": a} for i, op, a in steps], "answer": {"from": steps[-1][0], "field": "rows_total", "kind": "count", **answer}})


REACH = ("s1", "earliest_arrival", {"sources": [0], **WINDOW, "limit": 1000})


def codes(store, p, text="node 0 user 3"):
    return {v.code for v in verify_plan(p, text, store.stats, store.now_tt)}


def test_the_algebra_has_thirteen_operators_with_schemas():
    assert len(REGISTRY) == 13 and len(tool_manifest()) == 13
    for tool in tool_manifest():
        assert {"as_of_tt", "limit", "cursor"} <= set(tool["parameters"]["properties"]) and json.dumps(tool)


def test_every_violation_has_its_code(store):
    assert codes(store, plan(REACH)) == set()
    assert codes(store, plan(("s1", "no_such", {}))) == {"E_SCHEMA"}
    assert codes(store, plan(("s1", "khop_neighbourhood", {"seeds": [0], "k": 4, "t": T0}))) == {"E_SCHEMA"}
    assert codes(store, plan(("s1", "compute", {"fn": "count", "input": ref("s2.rows[*]")}), ("s2", "compute", {"fn": "filter", "input": ref("s1.rows[*]")}))) >= {"E_CYCLE"}
    assert codes(store, plan(REACH, ("s2", "compute", {"fn": "count", "input": ref("s9.rows[*]")}))) == {"E_SCOPE"}
    assert codes(store, plan(("s1", "earliest_arrival", {"sources": [0], "t_from": T0 // 1000, "t_to": T0}))) == {"E_TIME"}
    assert codes(store, plan(("s1", "diff_states", {"t1": T0, "t2": T0 + DAY, "as_of_tt": store.now_tt + 1}))) == {"E_TIME"}
    assert codes(store, plan(("s1", "version_history", {"ident": "77"}))) == {"E_GROUND"}
    assert codes(store, plan(REACH, field="total")) == {"E_FIELD"}
    assert codes(store, plan(REACH, ("s2", "count_motifs", {"pattern": "cyclic", "delta": 10**16, "nodes": ref("s1.rows[*].node")}))) == {"E_COST"}


def test_field_violations_list_the_legal_fields(store):
    (v,) = verify_plan(plan(REACH, field="rows[0].count"), "node 0", store.stats, store.now_tt)
    assert set(v.allowed) == {"source", "node", "arrival"}


def test_refusals_say_how_to_narrow(store):
    no = guard.refuse("count_motifs", {"pattern": "cyclic", "delta": 400 * HOUR}, store.stats, 20_000)
    assert no is not None and any("delta" in s for s in no.suggestions)
    assert guard.refuse("count_motifs", {"pattern": "cyclic", "delta": HOUR}, store.stats) is None


def test_references():
    assert Ref.parse("s1.rows[*].node").star and Ref.parse("s1.rows[2].w").at == "2" and Ref.parse("s1.rows_total").field == "rows_total"
    assert Ref.parse("s1.rows[0].w + 1") is None and Ref.parse("s1") is None


def test_pages_follow_each_other_and_say_if_they_are_complete(spark):
    df = spark.range(25).selectExpr("id % 5 as a", "id as b")
    seen, cursor = [], None
    while True:
        p = paging.page(df, ["a", "b"], 10, cursor)
        seen += [(r["a"], r["b"]) for r in p.rows]
        assert p.rows_total == 25 and not p.complete
        cursor = p.cursor
        if cursor is None:
            break
    assert seen == sorted((i % 5, i) for i in range(25))
    assert paging.page(df, ["a", "b"], 25).complete and not paging.page(df, ["a", "b"], 24).complete
    assert paging.page(df.limit(0), ["a", "b"]).complete


def test_execution_is_repeatable(spark, store):
    p = plan(REACH, ("s2", "count_motifs", {"pattern": "cyclic", "delta": 6 * HOUR, "nodes": ref("s1.rows[*].node")}), field="rows[0].count")
    digests = set()
    before = spark.conf.get("spark.sql.shuffle.partitions")
    for n in ("1", "8"):
        spark.conf.set("spark.sql.shuffle.partitions", n)
        digests.add(tuple(s.page.result_digest for s in execute_plan(p, store).steps.values()))
    spark.conf.set("spark.sql.shuffle.partitions", before)
    assert len(digests) == 1
    assert execute_plan(p, store).answer == execute_plan(p, store, consume="full").answer


def cut_plan(limit):
    return plan(("s1", "earliest_arrival", {"sources": [0], **WINDOW, "limit": limit}), ("s2", "compute", {"fn": "count", "input": ref("s1.rows[*]")}), field="rows[0].value")


def test_a_cut_page_taints_what_depends_on_it(store):
    whole, cut = execute_plan(cut_plan(1000), store), execute_plan(cut_plan(5), store)
    assert cut.answer == 5 and not cut.steps["s1"].complete and cut.steps["s2"].tainted and not whole.steps["s2"].tainted
    answer = Answer("count", 5, [Claim("count", 5, ("s2",), "rows[0].value", "s2")])
    assert answer_level(check_claims(answer, cut)) == "weak"
    untracked = execute_plan(cut_plan(5), store, taint=False)
    assert answer_level(check_claims(answer, untracked, taint=False)) == "supported"
    assert execute_plan(cut_plan(5), store, consume="full").answer == whole.answer


def test_claims(store):
    done = execute_plan(plan(REACH), store)
    level = lambda *c: answer_level(check_claims(Answer("x", None, list(c)), done, store))
    n = done.steps["s1"].page.rows_total
    assert level(Claim("count", n, ("s1",), "rows_total")) == "supported"
    assert level(Claim("count", n + 1, ("s1",), "rows_total")) == "unsupported"
    assert level(Claim("count", n, ("s1",), "rows_total", pointer="s7")) == "unsupported"
    assert level(Claim("count", n, ())) == "unsupported"
    assert level(Claim("entity", ["1", "2"], ("s1",))) == "supported" and level(Claim("entity", ["1", "999"], ("s1",))) == "unsupported"
    assert level(Claim("pattern", "wrong", ("s1",))) == "supported"  # reported, not gated
    assert check_claims(Answer("x", None, [Claim("pattern", done.steps["s1"].page.result_digest, ("s1",))]), done, store)[0].level == "supported"


def test_gate_drops_and_abstains(store):
    done = execute_plan(plan(REACH), store)
    n = done.steps["s1"].page.rows_total
    both = Answer("count", n, [Claim("count", n, ("s1",), "rows_total"), Claim("count", n + 1, ("s1",), "rows_total")])
    assert gate(both, check_claims(both, done)).dropped == [1]
    wrong = Answer("count", n + 1, [both.claims[1]])
    assert gate(wrong, check_claims(wrong, done)).answer is None


def test_dropped_members_cannot_be_seen(store):
    done = execute_plan(plan(REACH, field="rows[*].node"), store)
    answer = Answer("entity_set", done.answer, [Claim("entity", [str(v) for v in done.answer], ("s1",))])
    wrong, trace = mutate(answer, done, "dropped_member", 1)
    assert answer_level(check_claims(wrong, trace)) == "supported"
    wrong, trace = mutate(answer, done, "fabricated_entity", 1)
    assert answer_level(check_claims(wrong, trace)) == "unsupported"


def test_suites_probes_and_repair(store):
    memo = {}
    tasks = make_tasks(store, "t", 1, only=("a01", "a04", "e01", "m02"), memo=memo)
    assert tasks and split_digest(tasks) == split_digest(make_tasks(store, "t", 1, only=("a01", "a04", "e01", "m02"), memo=memo))
    assert support_report(run_suite(tasks, store, System()))["accuracy"] == 1.0
    probes = make_probe_pairs(store, "t", 2, workloads.PINNED, workloads.VALID_AT, memo)
    assert len(probes) == 4 and support_report(run_suite(probes, store, System()))["accuracy"] == 1.0
    before = next(t for t in probes if t.probe_side == "before")
    assert execute_plan(drop_pin(before.plan), store).answer != before.gold
    outcome = repair_loop(NoisyPlanner({"field": 1.0, "unit": 1.0}, repair=1.0), tasks[0], store)
    assert not outcome.first_valid and outcome.plan is not None
    rows = run_suite(tasks, store, System(planner=NoisyPlanner({"field": 1.0}, repair=0.0), checks=()))
    assert not any(r["executed"] for r in rows)  # without checks the wrong field dies at run time
    noisy = run_suite(tasks, store, System(reporter=NoisyReporter(1.0)))
    assert not any(r["unsupported"] for r in noisy)


def test_failures_are_reported(store):
    with pytest.raises(PlanFailure):
        _ = execute_plan(plan(REACH, field="rows[999].node"), store).answer
    with pytest.raises(PlanFailure):
        execute_plan(plan(("s1", "version_history", {})), store)


def test_scores():
    assert correct("count", 3, 3) and not correct("count", True, 1) and not correct("value", None, 1.0)
    assert correct("interval", [0, 10], [5, 10]) and not correct("interval", [0, 10], [6, 10])
    assert correct("entity_set", {"rows": [{"uid": 1}, {"uid": 2}]}, ["2", "1"]) and not correct("entity_set", {"rows": [1, 2]}, ["1", "2"], strict_entities=True)


def test_bootstrap(spark):
    same = spark.createDataFrame([(str(i), 1, 1) for i in range(20)], "task string, a int, b int")
    assert tuple(paired_bootstrap(same, 200).first()) == (0.0, 0.0, 0.0)
    apart = spark.createDataFrame([(str(i), 1, i % 2) for i in range(40)], "task string, a int, b int")
    d, low, high = paired_bootstrap(apart, 500).first()
    assert d == 0.5 and 0.3 < low < 0.5 < high < 0.7


def test_bootstrap_sends_no_draws_to_the_driver(spark):
    from bitempo.eval.scoring import resampled_means

    scores = spark.createDataFrame([(str(i), 1, i % 2) for i in range(40)], "task string, a int, b int")
    plan = paired_bootstrap(scores)._jdf.queryExecution().executedPlan().toString().splitlines()
    depth = lambda line: len(line) - len(line.lstrip(" :+-"))
    for i, line in enumerate(plan):
        if "BroadcastHashJoin" in line:
            inner = [x for x in range(i + 1, len(plan)) if "BroadcastExchange" in plan[x] and depth(plan[x]) > depth(line)]
            for x in inner:
                below = next((y for y in range(x + 1, len(plan)) if depth(plan[y]) <= depth(plan[x])), len(plan))
                assert not any("Range (" in y for y in plan[x:below])
    placed = spark.createDataFrame([(i, float(i % 3)) for i in range(50)], "place int, d double")
    means = resampled_means(placed, 50, 20, 1)
    held = {r["place"]: r["d"] for r in placed.collect()}
    drawn = spark.range(20).selectExpr("id as resample", "explode(sequence(0, 49)) as slot").selectExpr("resample", "cast(pmod(xxhash64(resample, slot, 1), 50) as int) as place").collect()
    wanted = {r: sum(held[x["place"]] for x in drawn if x["resample"] == r) / 50 for r in range(20)}
    assert {r["resample"]: round(r["m"], 9) for r in means.collect()} == {r: round(m, 9) for r, m in wanted.items()}


def test_reporter_intervals(store):
    tasks = make_tasks(store, "t", 1, only=("a09",))
    done = execute_plan(tasks[0].plan, store)
    assert ScriptedReporter().report(tasks[0], done).value == tasks[0].gold


def test_rewrites_keep_answers(store):
    from bitempo.plans.rewrite import optimize

    motifs = ("s1", "find_motifs", {"pattern": "cyclic", "delta": 6 * HOUR, "t_from": T0, "t_to": T0 + 5 * DAY, "limit": 1000})
    p = plan(motifs, ("s2", "compute", {"fn": "count", "input": ref("s1.rows[*]")}), field="rows[0].value")
    fused = optimize(p)
    assert [s.op for s in fused.steps] == ["count_motifs"] and execute_plan(fused, store).answer == execute_plan(p, store).answer
    q = plan(REACH, ("s2", "compute", {"fn": "filter", "input": ref("s1.rows[*]"), "field": "node", "test": ["=", 7]}), field="rows[0].arrival")
    assert optimize(q).steps[0].args["targets"] == [7] and execute_plan(optimize(q), store).answer == execute_plan(q, store).answer
    assert len(optimize(plan(("s0", *motifs[1:]), REACH)).steps) == 1


def test_router_and_trace(store, tmp_path):
    from bitempo.plans.guard import CostRefusal
    from bitempo.plans.router import call_tool, export_trace, trace_report

    assert call_tool(store, "count_motifs", {"pattern": "cyclic", "delta": 6 * HOUR}).rows == [{"count": 9}]
    assert isinstance(call_tool(store, "count_motifs", {"pattern": "cyclic", "delta": 10**16}), CostRefusal)
    assert call_tool(store, "khop_neighbourhood", {"k": 9})[0].code == "E_SCHEMA"
    done = execute_plan(cut_plan(5), store)
    assert [r["state"] for r in trace_report(store, {"r": done}).orderBy("step_id").collect()] == ["cut page", "rests on a cut page"]
    export_trace(store, {"r": done}, str(tmp_path / "t"))
    assert store.spark.read.json(str(tmp_path / "t")).count() == 2


def test_cost_measures(spark, store, tmp_path):
    from bitempo.eval.costs import guard_calibration, store_bytes, tokens_per_task

    store.versions.write.parquet(str(tmp_path / "v"))
    assert store_bytes(spark, str(tmp_path / "v")) > 1000
    prompts = spark.createDataFrame([("x" * 100,), ("x" * 200,)], "prompt string")
    assert tuple(tokens_per_task(prompts).first()) == (2, 97.5)
    (row,) = guard_calibration(store, [("earliest_arrival", {"sources": [0], **WINDOW})])
    assert row[1] >= row[2] > 0


def test_table_form_checks_orderings_and_patterns(spark):
    from bitempo.claims.verifier import check_claims_table

    evidence = spark.createDataFrame([("r", "s1", None, ["0", "5", "9", "12"], True, False, "d1"), ("r", "s2", None, ["0", "5"], False, False, "d2")], "run_id string, step_id string, number double, ids array<string>, complete boolean, tainted boolean, digest string")
    rows = [
        (0, "ordering", ["s1"], 0, 5, 9, 12, "before", None), (1, "ordering", ["s1"], 0, 5, 9, 12, "after", None), (2, "ordering", ["s1"], 0, 5, 9, 13, "before", None),
        (3, "pattern", ["s1"], None, None, None, None, None, "d1"), (4, "pattern", ["s1"], None, None, None, None, None, "d2"), (5, "pattern", ["s2"], None, None, None, None, None, "d2"),
        (6, "ordering", ["s2"], 0, 5, 0, 5, "equals", None),
    ]
    claims = spark.createDataFrame([("r", "a", c, k, cites, None, None, None, *more) for c, k, cites, *more in rows], "run_id string, answer_id string, claim_id int, kind string, cites array<string>, pointer string, number double, ids array<string>, a_s long, a_e long, b_s long, b_e long, relation string, digest string")
    got = {r["claim_id"]: r["level"] for r in check_claims_table(claims, evidence).collect()}
    assert got == {0: "supported", 1: "unsupported", 2: "unsupported", 3: "supported", 4: "unsupported", 5: "weak", 6: "weak"}
    plain = claims.drop("a_s", "a_e", "b_s", "b_e", "relation", "digest")
    assert {r["level"] for r in check_claims_table(plain, evidence.drop("digest")).collect()} == {"unsupported"}


def test_pins_reach_intervals_and_names(store):
    from bitempo.plans.registry import REGISTRY

    pairs = lambda **a: REGISTRY["interval_pairs"].run(store, {"a": {}, "b": {}, "relations": ["overlaps"], "match": "src", **a}).count()
    assert 0 == pairs(as_of_tt=T0 - 1) <= pairs(as_of_tt=T0 + 5 * DAY) < pairs()
    names = lambda **a: REGISTRY["resolve_names"].run(store, {"text": "3", "mode": "exact", **a}).where("type = 'user'").count()
    assert names(as_of_tt=T0 - DAY) == 0 and names() == 1


def test_estimates_follow_seeds_and_node_sets(store):
    from bitempo.plans.guard import estimate

    one, many = ({"seeds": s, "k": 1, "t": T0} for s in ([1], ref("s1.rows[*].node")))
    assert estimate("khop_neighbourhood", one, store.stats) < estimate("khop_neighbourhood", many, store.stats)
    motif = {"pattern": "cyclic", "delta": DAY}
    assert estimate("count_motifs", {**motif, "nodes": [1, 2]}, store.stats) < estimate("count_motifs", motif, store.stats)


def test_planted_structures_are_found_without_their_nodes(spark, sf):
    from bitempo import workloads

    rows = workloads.planted_study(spark, sf).collect()
    assert len(rows) == 15 and {r["task"].split("-")[1] for r in rows} == {"cyclic", "feed_forward", "ping_pong", "path", "burst"}
    assert all(r["correct"] for r in rows), [r["task"] for r in rows if not r["correct"]]
