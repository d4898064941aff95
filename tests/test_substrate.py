import random

import oracles
import pytest
from pyspark.sql import functions as F

from bitempo.functions import canon, timeaxis
from bitempo.substrate.clock import stamp_transaction_time
from bitempo.substrate.fold import decide_outcomes, fold_identities, fold_versions, outcomes_of
from bitempo.substrate.log import FileStore, MemoryStore, OPS, assert_fact, attempt, correct_fact, new_only, operations, read_log, replay, retract_fact
from bitempo.substrate.segments import belief_at, segment_versions
from bitempo.substrate.snapshots import latest_before, overlap_violations, pinned_digest, scope, snapshot

OPEN = timeaxis.OPEN_END


def rows(df, *names):
    return sorted(tuple(r[n] for n in names) for r in df.collect())


def test_worked_example(spark):
    ops = operations(spark, [assert_fact(1, "e", 0, 100, 1.0), correct_fact(2, "e", 40, 60, 2.0)])
    versions = fold_versions(attempt(ops).where("outcome = 'committed'"))
    assert rows(versions, "vt_s", "vt_e", "tt_s", "tt_e", "w") == [(0, 40, 2, OPEN, 1.0), (0, 100, 1, 2, 1.0), (40, 60, 2, OPEN, 2.0), (60, 100, 2, OPEN, 1.0)]
    assert rows(snapshot(versions, 50), "w") == [(2.0,)]
    assert rows(snapshot(versions, 50, 1), "w", "tt_e") == [(1.0, OPEN)]  # the closing lies after the pin


def _random(seed, cases=200):
    rnd, out, batch = random.Random(seed), {}, 0
    for c in range(cases):
        mine = []
        for i in range(rnd.randrange(1, 9)):
            batch += 1
            start, op = rnd.randrange(20), rnd.choice(("assert", "correct", "retract"))
            mine.append((batch, op, start, OPEN if op == "retract" else start + rnd.randrange(10), None if op == "retract" else float(i), batch))
        out[f"k{c}"] = mine
    return out


def _frame(spark, cases):
    ops = spark.createDataFrame([(b, 0, op, k, s, e, w, tt) for k, mine in cases.items() for b, op, s, e, w, tt in mine], OPS)
    return ops.withColumns({"tt": F.col("batch_id"), "log_shard": F.lit(0)})


def test_fold_equals_sequential_writing(spark):
    cases = _random(5)
    ops = _frame(spark, cases)
    got = {}
    for r in fold_versions(ops).collect():
        got.setdefault(r["ident"], []).append((r["vt_s"], r["vt_e"], r["tt_s"], r["tt_e"], r["w"]))
    codes = {r["batch_id"]: r["code"] for r in outcomes_of(fold_identities(ops)).collect()}
    for k, mine in cases.items():
        versions, wanted = oracles.fold(mine)
        assert sorted(got.get(k, [])) == versions
        assert all(codes[b] == c for b, c in wanted)


def test_fold_of_long_histories(spark):
    from bitempo.substrate.fold import fold_in_batches

    ops = _frame(spark, _random(10, 40))
    names = ("ident", "vt_s", "vt_e", "tt_s", "tt_e", "w")
    assert rows(fold_in_batches(ops), *names) == rows(fold_versions(ops), *names)


def test_segments_have_the_folds_snapshots_and_no_overlaps(spark):
    ops = _frame(spark, _random(6, 60))
    folded, segments = fold_versions(ops, require_existing=False), segment_versions(ops)
    assert overlap_violations(folded).count() == 0 and overlap_violations(segments).count() == 0
    for t, tt in ((3, None), (12, 150), (19, 90)):
        wanted = rows(snapshot(folded, t, tt), "ident", "w")
        assert rows(snapshot(segments, t, tt), "ident", "w") == wanted == rows(belief_at(ops, t, tt), "ident", "w")


def test_pinned_results_never_change(spark):
    ops = _frame(spark, _random(7, 40))
    early = ops.where("tt <= 100")
    assert pinned_digest(fold_versions(early), 90) == pinned_digest(fold_versions(ops), 90)
    assert pinned_digest(fold_versions(ops), 90) != pinned_digest(fold_versions(ops), 150)


def test_failed_batches_are_atomic_across_identities(spark):
    # batch 3 fails on z, so its part on e is void; batch 4 then finds e unchanged
    ops = operations(spark, [assert_fact(1, "e", 0, 100, 1.0), retract_fact(2, "y", 5), correct_fact(3, "e", 40, 60, 9.0), correct_fact(3, "z", 0, 5, 9.0, seq=1), correct_fact(4, "e", 10, 20, 2.0), assert_fact(5, "y", 7, 7, 1.0)])
    stamped = stamp_transaction_time(ops.withColumn("log_shard", F.lit(0)))
    found = {r["batch_id"]: r["fail_code"] for r in decide_outcomes(stamped).collect()}
    assert found == {1: None, 2: "F_NOTHING_TO_RETRACT", 3: "F_NOTHING_TO_CORRECT", 4: None, 5: "F_EMPTY_INTERVAL"}
    versions = fold_versions(attempt(ops).where("outcome = 'committed'"))
    assert versions.where("w = 9.0").count() == 0 and versions.where("w = 2.0").count() == 1


def test_replay_gives_one_digest_on_every_backend(spark, tmp_path):
    log = attempt(_frame(spark, _random(8, 30)).drop("tt", "log_shard"))
    assert log.where("outcome = 'failed'").count() > 0
    stores = [FileStore(spark, str(tmp_path / "p")), FileStore(spark, str(tmp_path / "o"), "orc"), MemoryStore(spark)]
    assert len({replay(log, s) for s in stores}) == 1
    kept = FileStore(spark, str(tmp_path / "l"), partitions=("log_shard",))
    kept.append("log", log)
    again = read_log(kept).select(*log.columns)
    assert replay(again, MemoryStore(spark)) == replay(log, MemoryStore(spark))
    assert new_only(log, again).count() == 0


def test_clock_is_strict_and_never_behind(spark):
    rnd = random.Random(1)
    data = [(i % 3, i, rnd.randrange(50)) for i in range(300)]
    got = stamp_transaction_time(spark.createDataFrame(data, "log_shard int, batch_id long, phys long"), high_water=20).collect()
    for shard in range(3):
        times = [(r["batch_id"], r["phys"], r["tt"]) for r in got if r["log_shard"] == shard]
        times.sort()
        last = 20
        for _, phys, tt in times:
            assert tt > last and tt >= phys
            last = tt


def test_as_of_join(spark):
    states = spark.createDataFrame([(1, 10, "a"), (1, 20, "b"), (2, 5, "c")], "k int, t long, v string")
    events = spark.createDataFrame([(1, 20), (1, 21), (1, 9), (2, 6)], "k int, t long")
    assert sorted((r["k"], r["t"], r["v"] or "") for r in latest_before(events, states, "k", "t", "v").collect()) == [(1, 9, ""), (1, 20, "a"), (1, 21, "b"), (2, 6, "c")]


def test_store_digest_ignores_order_and_partitions_but_not_counts(spark):
    df = spark.range(500).select("id", (F.col("id") / 7).alias("x"), F.lit(-0.0).alias("z"))
    assert canon.store_digest(df) == canon.store_digest(df.repartition(7).orderBy(F.desc("id")))
    assert canon.store_digest(df) != canon.store_digest(df.union(df.limit(1)))
    assert canon.store_digest(df.union(df)) != canon.store_digest(df.limit(0))


def test_micros_do_not_depend_on_the_session_zone(spark, sf):
    events = spark.read.parquet(f"{sf}/events.parquet").limit(50)
    before = rows(events.select(timeaxis.micros("ts").alias("t")), "t")
    zone = spark.conf.get("spark.sql.session.timeZone")
    spark.conf.set("spark.sql.session.timeZone", "America/New_York")
    try:
        assert rows(events.select(timeaxis.micros("ts").alias("t")), "t") == before
    finally:
        spark.conf.set("spark.sql.session.timeZone", zone)


def test_allen_relations_partition_all_pairs(spark):
    pairs = [(a, b, c, d) for a in range(4) for b in range(a + 1, 5) for c in range(4) for d in range(c + 1, 5)]
    df = spark.createDataFrame(pairs, "a long, b long, c long, d long").withColumn("r", timeaxis.allen("a", "b", "c", "d")).withColumn("i", timeaxis.allen("c", "d", "a", "b"))
    for r in df.collect():
        assert r["r"] == oracles.relation((r["a"], r["b"]), (r["c"], r["d"])) and timeaxis.INVERSE[r["r"]] == r["i"]


def test_open_end_does_not_overflow(spark):
    df = spark.createDataFrame([(OPEN,), (5,)], "t long")
    assert rows(df.select(timeaxis.later("t", 10).alias("t")), "t") == [(15,), (OPEN,)]


def test_scope_reaches_the_scan(spark, tmp_path):
    fold_versions(_frame(spark, _random(9, 5))).write.parquet(str(tmp_path / "v"))
    plan = scope(spark.read.parquet(str(tmp_path / "v")), 7)._jdf.queryExecution().toString()
    assert "PushedFilters" in plan and "LessThanOrEqual(tt_s,7)" in plan and "GreaterThan(tt_e,7)" in plan


@pytest.mark.parametrize("text,wanted", [("a<<b>>\\", "<<data>>\na\\<\\<b\\>\\>\\\\\n<</data>>"), (None, "<<data>>\n\n<</data>>"), ("x\x00y" * 3000, None)])
def test_fence(spark, text, wanted):
    from bitempo.functions.text import FENCE_CLOSE, FENCE_OPEN, fence

    got = spark.createDataFrame([(text,)], "t string").select(fence("t", 2000).alias("f")).first()["f"]
    assert wanted is None or got == wanted
    assert got.count(FENCE_OPEN) == 1 and got.count(FENCE_CLOSE) == 1 and len(got) < 2100


def test_worked_example_is_of_the_customers(spark, sf):
    from bitempo.queries import QUERIES

    found = QUERIES["version_fold_worked_example"](spark, sf)
    assert any(f.endswith("customer.parquet") for f in found.inputFiles())
    assert found.count() == 4 * spark.read.parquet(f"{sf}/customer.parquet").count()


def test_store_digest_deals_no_rows_out(spark):
    df = spark.range(1000).selectExpr("id", "id * 0.5 as x")
    spark.sparkContext.setJobGroup("digest-stages", "stages of one digest")
    canon.store_digest(df)
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    tracker = spark.sparkContext.statusTracker()
    stages = {s for j in tracker.getJobIdsForGroup("digest-stages") for s in tracker.getJobInfo(j).stageIds}
    assert 1 <= len(stages) <= 3  # one row for each task, then their sum
