from bitempo.baselines import retrieval
from bitempo.eval import harness
from bitempo.eval.tasks import Task
from bitempo.plans.ir import Plan
from bitempo.plans.store import Stats
from bitempo.sources import corpora


def test_all_prompts_at_once_find_what_each_finds(spark, sf):
    reader = retrieval.ChunkRetrieval(corpora.message_edges(spark, sf), n=24)
    prompts = {"one": "user 3 purchase", "two": "What was the value of user 7 at time 5?", "none": "?!", "odd": "zzz"}
    table = spark.createDataFrame(list(prompts.items()), "task string, prompt string")
    got = [(r["task"], r["place"], r["chunk"], r["score"]) for r in retrieval.retrieve_for_all(reader.weights, table, 4).collect()]
    want = [(t, i, r["chunk"], r["score"]) for t, p in prompts.items() for i, r in enumerate(retrieval.retrieve_chunks(reader.weights, p, 4).orderBy("score", ascending=False).collect(), 1)]
    assert sorted((t, i, s) for t, i, _, s in got) == sorted((t, i, s) for t, i, _, s in want)
    assert {(t, c) for t, _, c, _ in got} == {(t, c) for t, _, c, _ in want} and {t for t, *_ in got} == {"one", "two"}


def test_equal_budget_makes_plans_until_it_is_spent(monkeypatch):
    class Planner:
        made = 0

        def plan(self, task, feedback, attempt):
            assert feedback == [] and attempt == self.made
            self.made += 1
            return Plan.parse({"steps": [{"id": "s1", "op": "no_such_operator", "args": {}}], "answer": {"from": "s1", "field": "rows_total", "kind": "count"}})

    class Store:
        stats, now_tt = Stats(), 1

    task = Task("s", "t", "T1", "a01", "?", "count", None, 1)
    for spend, wanted in ((False, 1), (True, 4)):
        planner = Planner()
        row = harness.run_task(task, Store(), harness.System("x", planner, checks=(), budget=3, spend=spend))
        assert planner.made == row["generations"] == wanted and not row["executed"] and not row["emitted"]
